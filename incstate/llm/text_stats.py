"""Statistics of whole texts, computed for a slice of documents at a time."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from incstate.llm.common import Ragged, mix64

_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[list(b"0123456789")] = True
_UPPER = np.zeros(256, bool)
_UPPER[ord("A") : ord("Z") + 1] = True
_LOWER = np.zeros(256, bool)
_LOWER[ord("a") : ord("z") + 1] = True
_STOP = np.zeros(256, bool)
_STOP[list(b".,;:!?")] = True

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
SHARES = (
    "log_words", "mean_chars", "symbol_share", "dup_line_share", "repeat_share", "upper_share",
    "shout_share", "distinct_share", "digit_share", "short_share", "line_share", "stop_share",
)


def _per_doc(r: Ragged, mask: np.ndarray) -> np.ndarray:
    run = np.concatenate(([0], np.cumsum(mask)))
    return run[r.bounds[1:]] - run[r.bounds[:-1]]


def _distinct(r: Ragged, key: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Number of distinct keys of each document."""
    held = key ^ mix64(doc.astype(np.uint64) + np.uint64(1))
    order = np.argsort(held)
    new = np.concatenate(([True], np.diff(held[order]) != 0)) if len(held) else np.zeros(0, bool)
    return np.bincount(doc[order[new]], minlength=r.n)


def stats(texts: pa.Array) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """The ``COUNTS`` of each text and a matrix of its ``SHARES``; a null text counts as empty."""
    r = Ragged(texts)
    raw, n = r.bytes, r.counts
    inside = np.zeros(len(raw) + 1, np.int8)
    np.add.at(inside, r.starts, 1)
    np.add.at(inside, r.ends, -1)
    inside = np.cumsum(inside[:-1]) > 0
    chars = _per_doc(r, inside & ((raw & 0xC0) != 0x80))
    symbols = _per_doc(r, _SYMBOL[raw])
    h = r.hashes()

    feed = np.flatnonzero(raw == 10)
    begin = np.sort(np.concatenate((r.bounds[:-1], feed + 1)))
    doc = np.searchsorted(r.bounds, begin, "right") - 1
    # A feed that ends a text opens an empty last line, whose start is the next text's.
    fits = doc < r.n
    begin, doc = begin[fits], doc[fits]
    end = np.minimum(np.append(feed, len(raw))[np.searchsorted(feed, begin)], r.bounds[doc + 1])
    worded = np.searchsorted(r.starts, end) > np.searchsorted(r.starts, begin)
    begin, end, doc = begin[worded], end[worded], doc[worded]
    pairs = np.unique(np.stack((begin, end, doc)), axis=1) if len(begin) else np.zeros((3, 0), np.int64)
    begin, end, doc = pairs
    lines = np.bincount(doc, minlength=r.n)
    dup_lines = lines - _distinct(r, r.hash_of(begin, end), doc)

    repeat = np.zeros(len(h) + 3, np.int32)
    room = np.repeat(r.first[1:], n) - np.arange(len(h)) >= 3
    at = np.flatnonzero(room)
    key = mix64(h[at] + h[at + 1] * np.uint64(0xD6E8FEB86659FD93) + h[at + 2] * np.uint64(0xA0761D6478BD642F))
    key ^= mix64(r.doc[at].astype(np.uint64) + np.uint64(1))
    order = np.argsort(key)
    new = np.concatenate(([True], np.diff(key[order]) != 0)) if len(at) else np.zeros(0, bool)
    head = np.flatnonzero(new)
    often = np.repeat(np.diff(np.append(head, len(at))) > 1, np.diff(np.append(head, len(at))))
    hit = at[order[often]]
    np.add.at(repeat, hit, 1)
    np.add.at(repeat, hit + 3, -1)
    covered = np.cumsum(repeat)[: len(h)] > 0
    repeats = np.bincount(r.doc[covered], minlength=r.n)

    # Upper and lower letters of ASCII and of the two-byte block after 0xC3.
    lead = np.concatenate(([False], raw[:-1] == 0xC3)) if len(raw) else np.zeros(0, bool)
    upper = _per_doc(r, _UPPER[raw] | (lead & (raw >= 0x80) & (raw <= 0x9E)))
    lower = _per_doc(r, _LOWER[raw] | (lead & (raw >= 0x9F) & (raw <= 0xBF)))
    words = np.maximum(n, 1)
    short = np.bincount(r.doc[(r.ends - r.starts) <= 3], minlength=r.n)
    last = raw[r.ends - 1] if len(h) else np.zeros(0, np.uint8)
    counts = dict(zip(COUNTS, (n, chars, symbols, dup_lines, repeats)))
    some = np.maximum(chars, 1)
    shares = np.column_stack([
        np.log1p(n), chars / words, symbols / some, dup_lines / np.maximum(lines, 1), repeats / words,
        upper / np.maximum(upper + lower, 1), np.bincount(r.doc[last == ord("!")], minlength=r.n) / words,
        _distinct(r, h, r.doc) / words, _per_doc(r, _DIGIT[raw]) / some, short / words, lines / words,
        np.bincount(r.doc[_STOP[last]], minlength=r.n) / words,
    ])
    return counts, shares
