"""Parquet tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_report(report: DataFrame, path: str, form: str = "json") -> None:
    """A report as JSON or CSV lines."""
    if form not in ("json", "csv"):
        raise ValueError("a report is json or csv")
    report.write.mode("overwrite").format(form).option("header", form == "csv").save(path)
