"""Circuits as text: one statement per line, ``kind(angle) q[target],q[control],...;`` and ``barrier;`` between nets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_STATEMENT = r"^\s*([A-Za-z]+)\s*(?:\(([-+0-9.eE]+)\))?\s+((?:q\[\d+\]\s*,?\s*)+);"


def parse_gate_text(lines: DataFrame) -> DataFrame:
    """``lines(circuit_id, line_no, value)`` to gates; ``barrier`` starts the next net, other lines are skipped."""
    order = Window.partitionBy("circuit_id").orderBy("line_no")
    bar = F.col("value").rlike(r"^\s*barrier\b").cast("long")
    seen = lines.withColumn("net_no", F.sum(bar).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    hit = seen.where(F.col("value").rlike(_STATEMENT) & ~F.col("value").rlike(r"^\s*(barrier|qreg|creg|include|OPENQASM)\b"))
    qubits = F.transform(F.regexp_extract_all("value", F.lit(r"q\[(\d+)\]"), 1), lambda q: q.cast("int"))
    angle = F.regexp_extract("value", _STATEMENT, 2)
    return hit.select(
        "circuit_id", F.row_number().over(order).cast("long").alias("gate_no"), "net_no",
        F.upper(F.regexp_extract("value", _STATEMENT, 1)).alias("kind"), F.element_at(qubits, 1).alias("target"),
        F.slice(qubits, 2, 62).alias("controls"), F.when(angle == "", None).otherwise(angle.cast("double")).alias("theta"),
    )


def read_gate_text(spark: SparkSession, path: str) -> DataFrame:
    """Gates of the text files in ``path``; a file is a circuit, numbered by its name's hash."""
    raw = spark.read.text(path, wholetext=True).select(F.xxhash64(F.input_file_name()).alias("circuit_id"), F.posexplode(F.split("value", "\n")).alias("line_no", "value"))
    return parse_gate_text(raw)


def gate_lines(gates: DataFrame) -> DataFrame:
    """``circuit_id, value``: each circuit as text, with a barrier between nets."""
    qubits = F.concat(F.array("target"), F.coalesce("controls", F.array().cast("array<int>")))
    names = F.array_join(F.transform(qubits, lambda q: F.concat(F.lit("q["), q.cast("string"), F.lit("]"))), ",")
    angle = F.when(F.col("theta").isNull(), F.lit("")).otherwise(F.concat(F.lit("("), F.col("theta").cast("string"), F.lit(")")))
    line = F.concat(F.lower("kind"), angle, F.lit(" "), names, F.lit(";"))
    nets = gates.groupBy("circuit_id", "net_no").agg(F.array_sort(F.collect_list(F.struct("gate_no", line.alias("line")))).alias("rows"))
    text = nets.select("circuit_id", F.struct("net_no", F.array_join(F.col("rows.line"), "\n").alias("text")).alias("net"))
    return text.groupBy("circuit_id").agg(F.array_sort(F.collect_list("net")).alias("nets")).select(
        "circuit_id", F.array_join(F.col("nets.text"), "\nbarrier;\n").alias("value")
    )


def write_gate_text(gates: DataFrame, path: str) -> None:
    gate_lines(gates).select("value").write.mode("overwrite").text(path)


def write_dot(dots: DataFrame, path: str) -> None:
    """``circuit_id, dot`` as text files."""
    dots.select("dot").write.mode("overwrite").text(path)
