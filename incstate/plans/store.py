"""Copy-on-write versions of blocks.

A slot stores only the blocks it writes; reading the state after a slot takes each block's latest version
up to it.  Versions are Parquet, one table per wave of slots that run together; the driver holds the folders' names and positions,
never blocks.
"""

from __future__ import annotations

import os
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from incstate.plans.wide import BLOCK_SCHEMA

START = "start"


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the cluster shares; a temporary one only in one process where none is set."""
    chosen = spark.sparkContext._jsc.sc().getCheckpointDir()
    if chosen.isDefined():
        return chosen.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
    spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="incstate-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


class CowStore:
    """Block versions of one circuit.

    ``materialize_all`` stores every block at every slot instead (the ablation without copy-on-write).
    """

    def __init__(self, spark: SparkSession, path: str | None = None, materialize_all: bool = False):
        self.spark = spark
        self.path = path or os.path.join(shared_folder(spark), f"versions-{uuid.uuid4().hex}")
        self.materialize_all = materialize_all
        self.order: list[str] = [START]
        #: Folders of each slot, oldest first; a later one overrides blocks of an earlier one.
        self.folders: dict[str, list[str]] = {}
        self.blocks: dict[str, set[int]] = {}

    def write(self, slot: str, blocks: DataFrame, ids: set[int]) -> None:
        """Store ``blocks`` (whose ids are ``ids``) as the newest version of a slot."""
        folder = f"{self.path}/{slot}-{uuid.uuid4().hex[:8]}"
        blocks.select("block_id", "re", "im").sortWithinPartitions("block_id").write.parquet(folder)
        self.folders.setdefault(slot, []).append(folder)
        self.blocks.setdefault(slot, set()).update(ids)

    def write_wave(self, made: list[tuple[str, DataFrame, set[int]]]) -> None:
        """Store the blocks of several slots by one job, as one table that is partitioned by slot."""
        if len(made) == 1:
            self.write(*made[0])
            return
        folder = f"{self.path}/wave-{uuid.uuid4().hex[:8]}"
        every = None
        for slot, blocks, _ in made:
            one = blocks.select(F.lit(slot).alias("slot"), "block_id", "re", "im")
            every = one if every is None else every.unionByName(one)
        every.sortWithinPartitions("slot", "block_id").write.partitionBy("slot").parquet(folder)
        for slot, _, ids in made:
            self.folders.setdefault(slot, []).append(f"{folder}/slot={slot}")
            self.blocks.setdefault(slot, set()).update(ids)

    def read(self, upto: int | None = None, wanted: set[int] | None = None) -> DataFrame:
        """Blocks after the slot at place ``upto`` of ``order`` (all slots if None), only ``wanted`` ones if given."""
        places = self.order if upto is None else self.order[: upto + 1]
        latest = {}
        for place, slot in enumerate(places):
            for k in self.blocks.get(slot, ()):
                latest[k] = place
        use = {p for k, p in latest.items() if wanted is None or k in wanted}
        parts = []
        for place in sorted(use):
            for nth, folder in enumerate(self.folders[places[place]]):
                part = self.spark.read.schema("block_id bigint, re array<double>, im array<double>").parquet(folder)
                parts.append(part.withColumn("at", F.struct(F.lit(place).alias("place"), F.lit(nth).alias("nth"))))
        if not parts:
            return self.spark.createDataFrame([], BLOCK_SCHEMA)
        every = parts[0]
        for part in parts[1:]:
            every = every.unionByName(part)
        if wanted is not None:
            every = every.where(within(wanted))
        newest = every.groupBy("block_id").agg(F.max_by(F.struct("re", "im"), "at").alias("v"))
        return newest.select(F.lit(0).cast("long").alias("circuit_id"), "block_id", "v.re", "v.im")

    def forget(self, slot: str) -> None:
        """Drop a slot; its blocks fall through to earlier versions from now on."""
        self.order.remove(slot)
        self.folders.pop(slot, None)
        self.blocks.pop(slot, None)

    def vacuum(self) -> int:
        """Delete folders that no slot points at; returns how many."""
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = hadoop.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(hadoop):
            return 0
        live = {f.removeprefix(f"{self.path}/") for held in self.folders.values() for f in held}
        waves = {f.split("/")[0] for f in live if "/" in f}
        gone = [s.getPath() for s in fs.listStatus(hadoop) if s.getPath().getName() not in live | waves]
        for wave in waves:
            slots = fs.listStatus(self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{wave}"))
            gone += [s.getPath() for s in slots if s.isDirectory() and f"{wave}/{s.getPath().getName()}" not in live]
        for path in gone:
            fs.delete(path, True)
        return len(gone)

    def stored(self) -> int:
        """Block versions that slots hold, without the start."""
        return sum(len(v) for k, v in self.blocks.items() if k != START)


def within(ids: set[int]) -> Column:
    """Whether a block is one of ``ids``, by runs of consecutive ones."""
    keep = F.lit(False)
    for lo, hi in _runs(sorted(ids)):
        keep |= F.col("block_id").between(lo, hi)
    return keep


def _runs(ids: list[int]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for k in ids:
        if out and k == out[-1][1] + 1:
            out[-1] = (out[-1][0], k)
        else:
            out.append((k, k))
    return out


def saving(written: int, slots: int, blocks: int) -> float:
    """Share of block versions that copy-on-write doesn't store."""
    return 1 - written / (slots * blocks) if slots and blocks else 0.0
