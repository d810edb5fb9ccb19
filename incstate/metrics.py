"""Cost and accuracy measures."""

from __future__ import annotations

import math
import resource
import time
from collections.abc import Callable
from statistics import mean, median

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def time_runs(run: Callable[[], object], repeats: int = 10) -> dict[str, float]:
    """Mean and median seconds of ``repeats`` runs."""
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        run()
        took.append(time.perf_counter() - began)
    return {"mean": mean(took), "median": median(took), "runs": repeats}


def time_inc(steps: Callable[[], list[Callable[[], object]]], repeats: int = 1) -> dict[str, float | list[float]]:
    """Seconds of an incremental run, one update after another: the sum over ``steps`` (made anew for each repeat) and each step's mean."""
    took = []
    for _ in range(repeats):
        one = []
        for step in steps():
            began = time.perf_counter()
            step()
            one.append(time.perf_counter() - began)
        took.append(one)
    per_step = [mean(x) for x in zip(*took)]
    return {"total": sum(per_step), "per_step": per_step, "runs": repeats}


def saturation(seconds: dict[int, float], gain: float = 0.05) -> int:
    """The number of cores from which the next larger one saves less than ``gain`` of the time."""
    cores = sorted(seconds)
    for a, b in zip(cores, cores[1:]):
        if seconds[a] - seconds[b] < gain * seconds[a]:
            return a
    return cores[-1]


def write_measures(rows: DataFrame, folder: str) -> None:
    """Add measure rows (with a column ``run``) to a table that is partitioned by run."""
    rows.write.mode("append").partitionBy("run").parquet(folder)


def wave_width(waves: DataFrame) -> DataFrame:
    """``circuit_id, widest, mean_width``: how many nodes of a graph can run together."""
    per = waves.groupBy("circuit_id", "wave").agg(F.count("*").alias("nodes"))
    return per.groupBy("circuit_id").agg(F.max("nodes").alias("widest"), F.avg("nodes").alias("mean_width"))


def speedup(base: list[float], ours: list[float]) -> dict[str, float]:
    """The ratio of totals (the headline form), and the arithmetic and geometric means of ratios."""
    ratios = [a / b for a, b in zip(base, ours, strict=True)]
    return {"total": sum(base) / sum(ours), "mean": mean(ratios), "geometric": math.exp(mean(map(math.log, ratios)))}


def cumulative(history: DataFrame, value: str, keys: list[str], order: str) -> DataFrame:
    """``history`` with the running sum of ``value``."""
    run = Window.partitionBy(*keys).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    return history.withColumn(f"cumulative_{value}", F.sum(value).over(run))


def peak_memory_gb() -> float:
    """Peak resident size of this process."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / (1 << 20)


def norm_error(rows: DataFrame) -> DataFrame:
    """``circuit_id, error``: how far the probabilities are from one in sum."""
    p = F.col("re") * F.col("re") + F.col("im") * F.col("im")
    return rows.groupBy("circuit_id").agg(F.abs(F.sum(p) - 1).alias("error"))


def fidelity(a: DataFrame, b: DataFrame) -> DataFrame:
    """``circuit_id, fidelity``: squared overlap of two row states; missing rows are zeros."""
    right = b.select("circuit_id", "idx", F.col("re").alias("br"), F.col("im").alias("bi"))
    met = a.join(right, ["circuit_id", "idx"])
    real = F.sum(F.col("re") * F.col("br") + F.col("im") * F.col("bi"))
    imag = F.sum(F.col("re") * F.col("bi") - F.col("im") * F.col("br"))
    return met.groupBy("circuit_id").agg((real * real + imag * imag).alias("fidelity"))


def max_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """``circuit_id, difference``: the largest distance of two amplitudes; missing rows are zeros."""
    right = b.select("circuit_id", "idx", F.col("re").alias("br"), F.col("im").alias("bi"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    gap = F.hypot(zero("re") - zero("br"), zero("im") - zero("bi"))
    return a.join(right, ["circuit_id", "idx"], "full_outer").groupBy("circuit_id").agg(F.max(gap).alias("difference"))


def circuit_stats(gates: DataFrame, levels: DataFrame | None = None) -> DataFrame:
    """``circuit_id, gates, cnots, depth``; depth is the number of nets, or of ``levels``."""
    base = gates.groupBy("circuit_id").agg(
        F.count("*").alias("gates"), F.sum((F.col("kind") == "CNOT").cast("long")).alias("cnots"), F.countDistinct("net_no").alias("depth")
    )
    if levels is None:
        return base
    return base.drop("depth").join(levels.groupBy("circuit_id").agg(F.max("level").alias("depth")), "circuit_id")
