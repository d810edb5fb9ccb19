"""States encoded from tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from incstate.sources.tables import table


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each embedding's 64 entries as amplitudes of 6 qubits, normalised: ``circuit_id, re, im``."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("circuit_id"), v.alias("v")).withColumn("norm", norm).select(
        "circuit_id", F.transform("v", lambda x: x / F.col("norm")).alias("re"), F.array_repeat(F.lit(0.0), 64).alias("im")
    )


def _rooted(binned: DataFrame) -> DataFrame:
    total = binned.agg(F.sum("w").alias("total"))
    return binned.crossJoin(F.broadcast(total)).select("idx", F.sqrt(F.col("w") / F.col("total")).alias("a"))


def histogram(spark: SparkSession, sf_dir: str, n: int = 10) -> DataFrame:
    """Square roots of the shares of part keys modulo ``2**n``: rows of one state."""
    rows = table(spark, sf_dir, "lineitem").groupBy(F.pmod("l_partkey", F.lit(1 << n)).alias("idx")).agg(F.count("*").cast("double").alias("w"))
    return _rooted(rows).select(F.lit(0).cast("long").alias("circuit_id"), "idx", F.col("a").alias("re"), F.lit(0.0).alias("im"))


def values(spark: SparkSession, sf_dir: str, n: int = 10) -> DataFrame:
    """Square roots of the shares of order value by customer modulo ``2**n``."""
    rows = table(spark, sf_dir, "orders").groupBy(F.pmod("o_custkey", F.lit(1 << n)).alias("idx")).agg(F.sum("o_totalprice").alias("w"))
    return _rooted(rows).select(F.lit(0).cast("long").alias("circuit_id"), "idx", F.col("a").alias("re"), F.lit(0.0).alias("im"))


def events(spark: SparkSession, sf_dir: str, n: int = 7) -> DataFrame:
    """Square roots of the shares of event value by user modulo ``2**n``, with a phase from the least ``k``."""
    k = F.get_json_object("props", "$.k").cast("int")
    rows = table(spark, sf_dir, "events").groupBy(F.pmod("user_id", F.lit(1 << n)).alias("idx")).agg(F.sum("value").alias("w"), F.min(k).alias("k"))
    total = rows.agg(F.sum("w").alias("total"))
    a, phase = F.sqrt(F.col("w") / F.col("total")), F.pi() * 2 * F.col("k") / 100
    return rows.crossJoin(F.broadcast(total)).select(
        F.lit(0).cast("long").alias("circuit_id"), "idx", (a * F.cos(phase)).alias("re"), (a * F.sin(phase)).alias("im")
    )
