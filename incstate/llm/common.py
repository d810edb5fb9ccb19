"""Shared pieces of the corpus operators: lineage cuts and ragged word arrays.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D.  UTF-8 never uses those values inside a
multi-byte character, so cutting bytes equals cutting characters.
"""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import hashlib
import os
import re
import tempfile
import time
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java regular expression of one word.
WORD = r"[^\x20\x09-\x0D]+"
#: Text bytes that the numpy kernels hold at a time; a longer single text is one slice of its own.
SLICE_BYTES = 1 << 20

#: Rows that go to a Python worker at a time; whole texts of this many rows are in memory on both sides.
ARROW_ROWS = 512

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32

try:
    _TRIM = ctypes.CDLL("libc.so.6").malloc_trim
except (OSError, AttributeError):
    _TRIM = None

_gave = 0.0
#: Masks of the first bytes of an eight-byte load.
_HEAD = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_STIR = np.uint64(0x9FB21C651E98DF25)
#: Words of this many bytes or more are hashed one by one.
LONG_WORD = 1024


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared checkpoint folder; one is made only in one process where the session names none."""
    context = spark.sparkContext
    chosen = context._jsc.sc().getCheckpointDir()
    if chosen.isDefined():
        return chosen.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", context.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="incstate-checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def bound_batches(df: DataFrame, rows: int = ARROW_ROWS) -> None:
    """Set the session's Arrow batches to ``rows``, few enough for rows with whole texts."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def cut(df: DataFrame) -> DataFrame:
    """Run ``df`` once and read it from the shared folder from then on; any executor may be lost afterwards."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


_tables: list[tuple[SparkSession, str]] = []


def _drop_tables() -> None:
    """Delete the session's written tables when the driver ends."""
    for spark, path in _tables:
        with contextlib.suppress(Exception):
            held = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            held.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(held, True)
    _tables.clear()


def written(df: DataFrame) -> DataFrame:
    """As :func:`cut`, as compressed columns, for wide or long tables; they go when the driver ends."""
    path = os.path.join(shared_dir(df.sparkSession), f"table-{uuid.uuid4().hex}")
    df.write.parquet(path)
    if not _tables:
        # Registered after the session's own, so that it runs before the session stops.
        atexit.register(_drop_tables)
    _tables.append((df.sparkSession, path))
    return df.sparkSession.read.schema(df.schema).parquet(path)


def word_count(text: Column) -> Column:
    """Number of words; 0 for null."""
    return F.coalesce(
        F.size(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")).cast("long"), F.lit(0).cast("long")
    )


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser, element by element."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class Ragged:
    """The words of some texts as flat arrays: byte bounds, document number and (on demand) 64-bit hashes."""

    def __init__(self, texts: pa.Array, lower: bool = False):
        texts = pc.fill_null(texts, "").cast(pa.large_string())
        bounds = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        data = texts.buffers()[2]
        raw = np.frombuffer(data, np.uint8)[bounds[0] : bounds[-1]] if data is not None else np.zeros(0, np.uint8)
        self.n = len(texts)
        self.bounds = bounds - bounds[0]
        self.bytes = _LOWER[raw] if lower else raw
        inside = ~_SPACE[self.bytes]
        edge = np.zeros(len(raw) + 1, bool)
        edge[self.bounds] = True
        before = np.concatenate(([False], inside))
        after = np.concatenate((inside, [False]))
        self.starts = np.flatnonzero(after & (~before | edge))
        self.ends = np.flatnonzero(before & (~after | edge))
        self.first = np.searchsorted(self.starts, self.bounds)
        self.counts = np.diff(self.first)
        self.doc = np.repeat(np.arange(self.n), self.counts)

    def hashes(self) -> np.ndarray:
        """One 64-bit hash per word."""
        return self.hash_of(self.starts, self.ends)

    def hash_of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """One 64-bit hash for each run of bytes, eight bytes at a time."""
        padded = np.zeros(len(self.bytes) + 8, np.uint8)
        padded[:-8] = self.bytes
        eight = np.ndarray((len(self.bytes) + 1,), "<u8", padded, strides=(1,))
        size = ends - starts
        out = size.astype(np.uint64) * _STIR
        rest, at = np.arange(len(starts)), 0
        while len(rest) and at < LONG_WORD:
            left = size[rest] - at
            held = (out[rest] ^ (eight[starts[rest] + at] & _HEAD[np.minimum(left, 8)])) * _STIR
            out[rest] = held ^ (held >> np.uint64(29))
            at += 8
            rest = rest[left > 8]
        for k in rest.tolist():
            out[k] = int.from_bytes(hashlib.blake2b(self.bytes[starts[k] : ends[k]].tobytes(), digest_size=8).digest(), "little")
        return mix64(out)


def slices(texts: pa.Array, most: int = SLICE_BYTES, pause: float = 0.0) -> Iterator[tuple[int, int]]:
    """Consecutive row ranges of at most ``most`` text bytes (at least one row each).

    When they have been worked on, freed memory goes back to the system if that was ``pause`` seconds ago.
    """
    size = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < len(size):
        done = int(size[at - 1]) if at else 0
        stop = max(at + 1, int(np.searchsorted(size, done + most, "right")))
        yield at, stop
        at = stop
    give_back(pause)


def give_back(pause: float = 0.0) -> None:
    """Return freed memory to the system, for the other workers of this machine."""
    global _gave
    if time.monotonic() - _gave < pause:
        return
    _gave = time.monotonic()
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def flat(array: pa.Array | pa.ChunkedArray) -> pa.Array:
    return array.combine_chunks() if isinstance(array, pa.ChunkedArray) else array
