"""Token counts by rank-synchronous byte-pair merging over ragged arrays.

Texts are cut into pre-tokens; pre-tokens not met before are held together as one flat array of symbols.
In each round every sequence finds its lowest-ranked adjacent pair and merges all of that pair's
occurrences at once, from the left where they overlap; sequences without a ranked pair leave.  What
survives are the tokens.  A pair that contains a new symbol always ranks after the merge that made the
symbol, so merging a sequence's lowest rank everywhere at once equals merging one pair at a time.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import bound_batches, flat, slices

VOCABULARY = "byte_bpe_50k.json"
LIMIT = 1024
#: Pre-tokens whose counts a worker remembers before it starts anew.
REMEMBERED = 400_000

#: The published splitting pattern of byte-level vocabularies.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def _byte_symbols() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class PairRanks:
    """Ranks and results of merges, in a few open tables probed with whole arrays."""

    def __init__(self, pairs: np.ndarray, ranks: np.ndarray, made: np.ndarray):
        self.tables = []
        self.bits = max(8, int(len(pairs)).bit_length() + 3)
        draw = np.random.default_rng(1)
        while len(pairs):
            factor = draw.integers(1, 1 << 62, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
            slot = self._slot(pairs, factor)
            key = np.full(1 << self.bits, -1, np.int64)
            value = np.zeros(1 << self.bits, np.int64)
            key[slot], value[slot] = pairs, (ranks << 32) | made
            self.tables.append((factor, key, value))
            lost = key[slot] != pairs
            pairs, ranks, made = pairs[lost], ranks[lost], made[lost]

    def _slot(self, pairs: np.ndarray, factor: np.uint64) -> np.ndarray:
        return ((pairs.astype(np.uint64) * factor) >> np.uint64(64 - self.bits)).astype(np.int64)

    def __call__(self, pairs: np.ndarray) -> np.ndarray:
        """``rank << 32 | symbol`` of each pair, or a value above all where there's none."""
        out = np.full(len(pairs), np.iinfo(np.int64).max)
        for factor, key, value in self.tables:
            slot = self._slot(pairs, factor)
            hit = key[slot] == pairs
            out[hit] = value[slot[hit]]
        return out


class RankMerger:
    """A byte-level vocabulary file as arrays."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        names = _byte_symbols()
        self.base = np.array([vocab[names[b]] for b in range(256)], np.int64)
        #: Symbols of a sequence's last byte; -1 where the vocabulary has none.
        suffix = spec["model"].get("end_of_word_suffix") or ""
        self.last = np.array([vocab.get(names[b] + suffix, -1) for b in range(256)], np.int64)
        self.width = max(vocab.values()) + 1
        merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        pairs = np.array([vocab[a] * self.width + vocab[b] for a, b in merges], np.int64)
        made = np.array([vocab[a + b] for a, b in merges], np.int64)
        self.ranks = PairRanks(pairs, np.arange(len(merges), dtype=np.int64), made)
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        self.cut = regex.compile(PATTERN)
        self.stop = regex.compile("|".join(regex.escape(s) for s in self.special)) if self.special else None
        self.known: dict[str, int] = {}

    def tokens(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All pieces' token ids, piece after piece, and the number of tokens of each."""
        sizes = np.array([len(p) for p in pieces], np.int64)
        raw = np.frombuffer(b"".join(pieces), np.uint8)
        symbol = self.base[raw]
        ends = np.cumsum(sizes)[sizes > 0] - 1
        symbol[ends] = self.last[raw[ends]]
        owner = np.repeat(np.arange(len(pieces)), sizes)
        place = np.arange(len(symbol))
        done: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        none = np.iinfo(np.int64).max
        found = self._pairs(symbol, owner)
        while len(symbol):
            start = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1])))
            size = np.diff(np.append(start, len(symbol)))
            least = np.minimum.reduceat(found, start)
            going = np.repeat(least != none, size)
            if not going.all():
                done.append((place[~going], symbol[~going], owner[~going]))
                symbol, owner, place, found = symbol[going], owner[going], place[going], found[going]
                least = np.repeat(least, size)[going]
            else:
                least = np.repeat(least, size)
            if not len(symbol):
                break
            at = np.flatnonzero(found == least)
            # Of overlapping occurrences take every other one, from the left.
            fresh = np.concatenate(([True], np.diff(at) != 1))
            run = np.flatnonzero(fresh)
            nth = np.arange(len(at)) - np.repeat(run, np.diff(np.append(run, len(at))))
            at = at[nth % 2 == 0]
            symbol[at] = found[at] & 0xFFFFFFFF
            keep = np.ones(len(symbol), bool)
            keep[at + 1] = False
            # Only pairs at a merged symbol and before it are new.
            stale = np.zeros(len(symbol), bool)
            stale[at] = True
            symbol, owner, place, found, stale = symbol[keep], owner[keep], place[keep], found[keep], stale[keep]
            stale[:-1] |= stale[1:]
            spot = np.flatnonzero(stale)
            found[spot] = self._at(symbol, owner, spot)
        if not done:
            return np.zeros(0, np.int64), np.zeros(len(pieces), np.int64)
        place, symbol, owner = (np.concatenate(x) for x in zip(*done))
        return symbol[np.argsort(place)], np.bincount(owner, minlength=len(pieces))

    def _pairs(self, symbol: np.ndarray, owner: np.ndarray) -> np.ndarray:
        return self._at(symbol, owner, np.arange(len(symbol)))

    def _at(self, symbol: np.ndarray, owner: np.ndarray, spot: np.ndarray) -> np.ndarray:
        """Of each place the rank entry of the pair that starts there within its sequence."""
        out = np.full(len(spot), np.iinfo(np.int64).max)
        ok = spot + 1 < len(symbol)
        ok[ok] = owner[spot[ok]] == owner[spot[ok] + 1]
        s = spot[ok]
        out[ok] = self.ranks(symbol[s] * self.width + symbol[s + 1])
        return out

    def split(self, text: str) -> tuple[list[str], int]:
        """Pre-tokens of a text and the number of special tokens among them."""
        if self.stop is None or not self.stop.search(text):
            return self.cut.findall(text), 0
        parts = self.stop.split(text)
        return [piece for part in parts for piece in self.cut.findall(part)], len(parts) - 1

    def counts(self, texts: list[str]) -> list[int]:
        """Number of tokens of each text."""
        cut = [self.split(t) for t in texts]
        if len(self.known) > REMEMBERED:
            self.known = {}
        new = list(set().union(*(set(p) for p, _ in cut)).difference(self.known))
        if new:
            for at in range(0, len(new), 100_000):
                part = new[at : at + 100_000]
                self.known.update(zip(part, self.tokens([p.encode() for p in part])[1].tolist()))
        known = self.known.__getitem__
        return [sum(map(known, pieces)) + special for pieces, special in cut]


_mergers: dict[str, RankMerger] = {}


def merger(path: str) -> RankMerger:
    """The worker's merger for a vocabulary file."""
    if path not in _mergers:
        _mergers[path] = RankMerger(path)
    return _mergers[path]


def token_counts(docs: DataFrame, vocabulary: str, limit: int = LIMIT) -> DataFrame:
    """``docs(doc_id, text)`` to ``doc_id, n_bytes, n_tokens, over_limit``, one row per input row.

    ``vocabulary`` is the path of a byte-level merge file, the same on every machine.  No begin or end
    tokens are added; the vocabulary's special strings count as one token each, as the library has them by
    default.  A null or empty text has no tokens.  Repeated rows and null ids are counted like others;
    other columns are ignored; an empty table gives no rows.  A very long text is worked on alone, whole.
    """

    @F.arrow_udf(T.LongType())
    def count(text: pa.Array) -> pa.Array:
        bpe = merger(vocabulary)
        text = pc.fill_null(flat(text), "")
        return pa.array([n for a, b in slices(text) for n in bpe.counts(text[a:b].to_pylist())], pa.int64())

    bound_batches(docs)
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", F.octet_length(text).cast("long").alias("n_bytes"), count(text).alias("n_tokens")).withColumn(
        "over_limit", F.col("n_tokens") > limit
    )
