"""Joins and windows that Spark lacks as operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], lo: str = "lo", hi: str = "hi", bin_size: int = 64) -> DataFrame:
    """Pairs of rows with equal ``keys`` whose closed intervals meet.

    Both sides are dealt to the bins they touch and joined by (keys, bin); a pair is kept in the first bin
    that both touch, so nothing is repeated and no distinct is needed.  ``right``'s columns get a prefix ``r_``.
    """
    bins = lambda df, a, b: df.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(a) / bin_size), F.floor(F.col(b) / bin_size))))
    renamed = right.select(*[F.col(c) if c in keys else F.col(c).alias(f"r_{c}") for c in right.columns])
    met = bins(left, lo, hi).join(bins(renamed, f"r_{lo}", f"r_{hi}"), [*keys, "_bin"])
    meets = (F.col(lo) <= F.col(f"r_{hi}")) & (F.col(f"r_{lo}") <= F.col(hi))
    first = F.col("_bin") == F.floor(F.greatest(F.col(lo), F.col(f"r_{lo}")) / bin_size)
    return met.where(meets & first).drop("_bin")


def asof_join(events: DataFrame, versions: DataFrame, keys: list[str], at: str, value: str) -> DataFrame:
    """``events`` with the ``value`` of the latest version at or before each one (null if none).

    Both sides are stacked and one window carries the last value forward, so there's one shuffle by keys.
    """
    a = events.select(*[F.col(c) for c in events.columns], F.lit(None).cast(versions.schema[value].dataType).alias(value), F.lit(1).alias("_side"))
    b = versions.select(*keys, at, value).withColumn("_side", F.lit(0))
    order = Window.partitionBy(*keys).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b, allowMissingColumns=True).withColumn(value, F.last(value, ignorenulls=True).over(order)).where("_side = 1").drop("_side")


def islands(rows: DataFrame, keys: list[str], lo: str = "lo", hi: str = "hi") -> DataFrame:
    """Overlapping intervals of equal ``keys`` fused: ``keys, lo, hi, n``."""
    order = Window.partitionBy(*keys).orderBy(lo, hi)
    ahead = F.max(hi).over(order.rowsBetween(Window.unboundedPreceding, -1))
    new = F.when(F.col(lo) <= ahead, 0).otherwise(1)
    nth = F.sum("_new").over(order.rowsBetween(Window.unboundedPreceding, 0))
    return (
        rows.withColumn("_new", new).withColumn("_nth", nth).groupBy(*keys, "_nth")
        .agg(F.min(lo).alias(lo), F.max(hi).alias(hi), F.count("*").alias("n")).drop("_nth")
    )
