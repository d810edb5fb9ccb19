"""Packing along a space-filling curve.

A document's hashed token vector is projected to a few dimensions, and its place on the Hilbert curve
through them is its sort key, so documents of like wording lie near each other.  The documents in that
order are one stream of tokens which is cut every ``SEQUENCE`` tokens; only the last sequence can fall
short.  A narrow table of (key, tokens) is range-sorted to find each document's place in the stream; the
token ids are written once, and moved once to meet their places.
"""

from __future__ import annotations

import os
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.llm.common import Ragged, bound_batches, cut, flat, slices, written
from incstate.llm.rank_bpe import RankMerger

VOCABULARY = "word_bpe_49k.json"
SEQUENCE = 4096
END_ID = 2
AXES = 4
AXIS_BITS = 10
HASHED_TERMS = 4096
#: Whole units of an axis.
AXIS_UNIT = 4096
#: Units whose ids a worker remembers before it starts anew, about 80 bytes each.
REMEMBERED = 1_000_000
#: Units that are looked up at a time, whatever the length of a text.
UNITS = 1 << 18
#: Closing signs that are taken off a word; a longer run stays on it.
MOST_CLOSING = 4


def hilbert_key(cells: np.ndarray, bits: int = AXIS_BITS) -> np.ndarray:
    """Place on the Hilbert curve of each row of ``cells`` (unsigned, below ``2**bits``), as an int.

    The curve's cube is halved ``bits`` times along every axis; at each level a cell's orientation
    says which axes to mirror and how to swap the first axis with another, from the coarsest level down,
    and the Gray code of the coordinates becomes the digits of the key.
    """
    x = cells.astype(np.int64).copy()
    n = x.shape[1]
    for level in range(bits - 1, 0, -1):
        low = (1 << level) - 1
        for axis in range(n):
            set_ = (x[:, axis] >> level) & 1 == 1
            x[:, 0] = np.where(set_, x[:, 0] ^ low, x[:, 0])
            swap = np.where(set_, 0, (x[:, 0] ^ x[:, axis]) & low)
            x[:, 0] ^= swap
            x[:, axis] ^= swap
    for axis in range(1, n):
        x[:, axis] ^= x[:, axis - 1]
    flip = np.zeros(len(x), np.int64)
    for level in range(bits - 1, 0, -1):
        flip = np.where((x[:, n - 1] >> level) & 1 == 1, flip ^ ((1 << level) - 1), flip)
    x ^= flip[:, None]
    key = np.zeros(len(x), np.int64)
    for level in range(bits - 1, -1, -1):
        for axis in range(n):
            key = (key << 1) | ((x[:, axis] >> level) & 1)
    return key


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
#: Signs that may close a word, without those of contractions and special tokens.
_CLOSING = np.zeros(256, bool)
_CLOSING[list(b"!#$%&*+,-./:;=?@^_~")] = True
#: Small letters of ASCII and Latin-1, which are one pre-token together.
_LETTERS = re.compile(rb"(?:[a-z]|\xc3[\x9f-\xb6\xb8-\xbf])+")


class _Growing:
    """An array that grows at its end."""

    def __init__(self, kind, width: int = 1):
        self.held, self.n = np.zeros((1024, width) if width > 1 else 1024, kind), 0

    def __len__(self) -> int:
        return self.n

    def add(self, more: np.ndarray) -> None:
        if self.n + len(more) > len(self.held):
            room = np.zeros((max(len(self.held) // 2, len(more)), *self.held.shape[1:]), self.held.dtype)
            self.held = np.concatenate((self.held, room))
        self.held[self.n : self.n + len(more)] = more
        self.n += len(more)


class _Numbers:
    """64-bit keys to running numbers, in one open table that is probed with whole arrays."""

    def __init__(self):
        self.bits, self.n = 16, 0
        self.key, self.number = np.zeros(1 << 16, np.uint64), np.zeros(1 << 16, np.int32)

    def _walk(self, key: np.ndarray):
        """Rounds of (indices still open, their slots)."""
        left, slot = np.arange(len(key)), (key >> np.uint64(64 - self.bits)).astype(np.int64)
        while len(left):
            open_ = yield left, slot
            left, slot = left[open_], (slot[open_] + 1) & ((1 << self.bits) - 1)

    def find(self, key: np.ndarray) -> np.ndarray:
        """The number of each key, -1 if it isn't known."""
        key = np.maximum(key, np.uint64(1))
        out = np.full(len(key), -1, np.int64)
        walk = self._walk(key)
        step = next(walk, None)
        while step is not None:
            left, slot = step
            held = self.key[slot]
            hit = held == key[left]
            out[left[hit]] = self.number[slot[hit]]
            try:
                step = walk.send(~hit & (held != 0))
            except StopIteration:
                break
        return out

    def add(self, key: np.ndarray) -> None:
        """Number new, distinct keys in turn."""
        key = np.maximum(key, np.uint64(1))
        if 2 * (self.n + len(key)) > len(self.key):
            used = self.key != 0
            old = self.key[used][np.argsort(self.number[used])]
            while 2 * (self.n + len(key)) > 1 << self.bits:
                self.bits += 1
            self.key, self.number = np.zeros(1 << self.bits, np.uint64), np.zeros(1 << self.bits, np.int32)
            key, self.n = np.concatenate((old, key)), 0
        walk = self._walk(key)
        step = next(walk, None)
        while step is not None:
            left, slot = step
            free = self.key[slot] == 0
            self.key[slot[free]] = key[left[free]]
            put = free & (self.key[slot] == key[left])
            self.number[slot[put]] = self.n + left[put]
            try:
                step = walk.send(~put)
            except StopIteration:
                break
        self.n += len(key)


class WordIds:
    """The library's ids for texts, put together from those of blank-separated words.

    The vocabulary drops white space and never joins across it, so a text's ids are its words' ids in
    turn.  It lowers case and never joins a letter with a sign either, so words are taken in small ASCII
    and Latin-1 letters and a word's closing signs apart from its stem; words with the bar of special
    tokens are left as they are.  Units are known by a 64-bit hash.  New ones of such letters alone are one
    pre-token each and are merged by rank as whole arrays; the others go to the library in long runs, with
    a mark of one known id between them.
    """

    MARK = "|"
    RUN = 2000

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.merger = RankMerger(path)
        mark = self._encode([self.MARK])[0]
        self.mark = int(mark[0]) if len(mark) == 1 else None
        self.axes = _axes()
        self._forget()

    def _forget(self) -> None:
        self.known = _Numbers()
        self.start, self.size, self.pool = _Growing(np.int32), _Growing(np.int32), _Growing(np.uint32)
        self.moved = _Growing(np.int32, AXES)

    def _encode(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, units: list[bytes], keys: np.ndarray) -> np.ndarray:
        """The numbers of new units."""
        kind = np.array([0 if _LETTERS.fullmatch(u) else 2 if self.mark is None or b"|" in u else 1 for u in units])
        letters, plain, barred = ([units[i] for i in np.flatnonzero(kind == k)] for k in range(3))
        made, size = self.merger.tokens(letters)
        ids, sizes = [made.astype(np.uint32)], [size]
        for at in range(0, len(plain), self.RUN):
            run = plain[at : at + self.RUN]
            code = self._encode([f" {self.MARK} ".join(u.decode() for u in run)])[0]
            edge = np.flatnonzero(code == self.mark)
            if len(edge) != len(run) - 1:
                raise AssertionError("a word gave the id of the mark")
            sizes.append(np.diff(np.concatenate(([-1], edge, [len(code)]))) - 1)
            ids.append(code[code != self.mark])
        for u in barred:
            ids += self._encode([u.decode()])
            sizes.append(np.array([len(ids[-1])]))
        size, ids = np.concatenate(sizes), np.concatenate(ids)
        order = np.argsort(kind, kind="stable")
        number = np.empty(len(keys), np.int64)
        number[order] = len(self.start) + np.arange(len(keys))
        self.known.add(keys[order])
        self.start.add(len(self.pool) + np.cumsum(size) - size)
        self.size.add(size)
        self.pool.add(ids)
        run = np.concatenate((np.zeros((1, AXES), np.int64), np.cumsum(self.axes[_slots(ids)], axis=0, dtype=np.int64)))
        ends = np.cumsum(size)
        self.moved.add(run[ends] - run[ends - size])
        return number

    def _numbers(self, r: Ragged, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        key = r.hash_of(starts, ends)
        number = self.known.find(key)
        new = np.flatnonzero(number < 0)
        if not len(new):
            return number
        if len(self.start) + len(new) > REMEMBERED:
            self._forget()
            new = np.arange(len(key))
        keys, first, which = np.unique(key[new], return_index=True, return_inverse=True)
        first = new[first]
        raw = memoryview(r.bytes)
        units = [bytes(raw[x:y]) for x, y in zip(starts[first].tolist(), ends[first].tolist())]
        number[new] = self._learn(units, keys)[which]
        return number

    def read(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All texts' ids, text after text, their numbers, and the sum of each text's hashed places."""
        r = Ragged(texts)
        starts, ends, doc = self._units(r)
        out, counts, moved = [np.zeros(0, np.uint32)], np.zeros(r.n, np.int64), np.zeros((r.n, AXES), np.int64)
        for at in range(0, len(starts), UNITS):
            s = slice(at, at + UNITS)
            number, of = self._numbers(r, starts[s], ends[s]), doc[s]
            size = self.size.held[number].astype(np.int64)
            total = np.cumsum(size)
            out.append(self.pool.held[np.repeat(self.start.held[number] - total + size, size) + np.arange(total[-1])])
            head = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1])))
            counts[of[head]] += np.add.reduceat(size, head)
            for axis in range(AXES):
                moved[of[head], axis] += np.add.reduceat(self.moved.held[number, axis], head, dtype=np.int64)
        return np.concatenate(out), counts, moved

    def ids(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All texts' ids, text after text, and their numbers."""
        return self.read(texts)[:2]

    @staticmethod
    def _units(r: Ragged) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Byte bounds of stems and closing signs, and the text of each; lowers ``r.bytes``."""
        raw, stem = r.bytes, r.ends.copy()
        barred = np.zeros(len(stem), bool)
        bars = np.flatnonzero(raw == ord("|"))
        barred[np.searchsorted(r.starts, bars, "right") - 1] = True
        r.bytes = _LOWER[raw]
        latin = np.flatnonzero(raw == 0xC3) + 1
        latin = latin[(raw[latin] < 0x9F) & (raw[latin] != 0x97)]
        r.bytes[latin] += 0x20
        for x, y in zip(r.starts[barred].tolist(), r.ends[barred].tolist()):
            r.bytes[x:y] = raw[x:y]
        more = np.flatnonzero(~barred)
        for _ in range(MOST_CLOSING):
            more = more[_CLOSING[raw[stem[more] - 1]]]
            stem[more] -= 1
            more = more[stem[more] > r.starts[more]]
        two = np.flatnonzero((stem > r.starts) & (stem < r.ends))
        last, before = raw[stem[two] - 1], raw[np.maximum(stem[two] - 2, 0)]
        letter = ((last | 32) >= ord("a")) & ((last | 32) <= ord("z"))
        letter |= (before == 0xC3) & (last >= 0x80) & (last <= 0xBF) & (last != 0x97) & (last != 0xB7) & (stem[two] - 2 >= r.starts[two])
        two = two[letter]
        count = np.ones(len(stem), np.int64)
        count[two] = 2
        at = np.cumsum(count) - count
        starts, ends = np.repeat(r.starts, count), np.repeat(r.ends, count)
        ends[at[two]] = starts[at[two] + 1] = stem[two]
        return starts, ends, np.repeat(r.doc, count)


_readers: dict[str, WordIds] = {}


def _axes(seed: int = 11) -> np.ndarray:
    """Whole-number places of the hashed terms, so that sums don't depend on their order."""
    return np.rint(AXIS_UNIT * np.random.default_rng(seed).standard_normal((HASHED_TERMS, AXES))).astype(np.int32)


def _slots(ids: np.ndarray) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(52)).astype(np.int64)


def place_keys(moved: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The Hilbert key of each document's hashed token vector; one without tokens lies in the middle."""
    point = moved / AXIS_UNIT / np.sqrt(np.maximum(counts, 1))[:, None]
    # The spread of one axis over its cells, by a logistic curve near the normal one.
    cell = np.floor((1 << AXIS_BITS) / (1 + np.exp(-1.702 * point))).astype(np.int64)
    return hilbert_key(np.clip(cell, 0, (1 << AXIS_BITS) - 1))


def packed_pieces(docs: DataFrame, vocabulary: str, sequence: int = SEQUENCE, end_id: int = END_ID, with_ids: bool = True) -> DataFrame:
    """``docs(doc_id, text)`` to one row per piece with its token ids (uint32, little-endian) as ``ids``.

    Columns: ``doc_id, start, length, ids, ids_crc32, doc_tokens, sequence_id, offset``.  A null or empty
    text is the end id alone, so every row has a piece; repeated rows and null ids are separate documents;
    equal keys are ordered by a hash of the id.  An empty table gives no pieces; other columns are ignored.
    Without ``with_ids`` the column ``ids`` is null.
    """

    @F.arrow_udf(T.StructType().add("ids", "binary").add("n", "long").add("key", "long"))
    def read(text: pa.Array) -> pa.Array:
        if vocabulary not in _readers:
            _readers[vocabulary] = WordIds(vocabulary)
        text = pc.fill_null(flat(text), "")
        ids, n, key = [], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for a, b in slices(text, pause=1.0):
            all_ids, counts, moved = _readers[vocabulary].read(text[a:b])
            key.append(place_keys(moved, counts))
            ends = np.cumsum(counts)
            # Ids fit two bytes in such vocabularies; four where they don't.
            kind = "<u2" if not len(all_ids) or all_ids.max() < 1 << 16 else "<u4"
            all_ids, head, end = memoryview(all_ids.astype(kind)), kind[-1].encode(), np.array([end_id], kind).tobytes()
            ids += [b"".join((head, all_ids[x:y], end)) for x, y in zip((ends - counts).tolist(), ends.tolist())]
            n.append(counts + 1)
        return pa.StructArray.from_arrays(
            [pa.array(ids, pa.binary()), pa.array(np.concatenate(n)), pa.array(np.concatenate(key))], names=["ids", "n", "key"]
        )

    @F.arrow_udf(T.ArrayType(T.StructType().add("start", "long").add("length", "long").add("ids", "binary").add("crc", "long")))
    def split(ids: pa.Array, begin: pa.Array) -> pa.Array:
        ends, marks, raw, crc = [0], [], [], []
        for packed, at in zip(flat(ids), begin.to_pylist()):
            packed = packed.as_buffer()
            held = np.frombuffer(packed, "<u" + packed[:1].to_pybytes().decode(), offset=1).astype("<u4")
            edge = [0, *range(sequence - at % sequence, len(held), sequence), len(held)]
            for x, y in zip(edge, edge[1:]):
                marks.append((x, y - x))
                crc.append(zlib.crc32(held[x:y]))
                raw.append(held[x:y].tobytes() if with_ids else None)
            ends.append(len(crc))
        place = np.array(marks, np.int64).reshape(-1, 2)
        parts = [pa.array(place[:, 0]), pa.array(place[:, 1]), pa.array(raw, pa.binary()), pa.array(crc, pa.int64())]
        return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.StructArray.from_arrays(parts, names=["start", "length", "ids", "crc"]))

    bound_batches(docs)
    held = written(
        docs.select("doc_id", read(F.coalesce("text", F.lit(""))).alias("r"))
        .select("doc_id", "r.*")
        .withColumn("row", F.monotonically_increasing_id())
        .withColumn("tie", F.xxhash64("doc_id"))
    )
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = cut(
        held.select("key", "tie", "row", "n").repartitionByRange(parts, "key", "tie", "row").withColumn("part", F.spark_partition_id())
    )
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # a row per task
    offsets = order.groupBy("part").agg(F.sum("n").alias("sum")).select("part", F.coalesce(F.sum("sum").over(before), F.lit(0)).alias("base"))
    within = Window.partitionBy("part").orderBy("key", "tie", "row").rowsBetween(Window.unboundedPreceding, -1)
    places = (
        order.withColumn("ahead", F.coalesce(F.sum("n").over(within), F.lit(0)))
        .join(F.broadcast(offsets), "part")
        .select("row", (F.col("base") + F.col("ahead")).alias("begin"))
    )
    return (
        held.select("doc_id", "n", "ids", "row").join(places, "row")
        .select("doc_id", F.col("n").alias("doc_tokens"), "begin", F.explode(split("ids", "begin")).alias("p"))
        .select(
            "doc_id", "p.start", "p.length", "p.ids", F.col("p.crc").alias("ids_crc32"), "doc_tokens",
            F.floor((F.col("begin") + F.col("p.start")) / F.lit(sequence)).cast("long").alias("sequence_id"),
            F.pmod(F.col("begin") + F.col("p.start"), F.lit(sequence)).alias("offset"),
        )
    )


def packing(docs: DataFrame, vocabulary: str, **kwargs) -> DataFrame:
    """:func:`packed_pieces` without the ids."""
    return packed_pieces(docs, vocabulary, with_ids=False, **kwargs).select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"
    )
