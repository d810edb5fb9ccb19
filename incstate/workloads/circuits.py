"""Circuits and edit logs derived from tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from incstate.functions.gates import KINDS
from incstate.sources.tables import table

GATE_COLUMNS = ["circuit_id", "gate_no", "net_no", "kind", "target", "control", "theta"]


def kind_of(code: Column) -> Column:
    return F.element_at(F.array(*[F.lit(k) for k in KINDS]), (code + 1).cast("int"))


def with_controls(gates: DataFrame) -> DataFrame:
    """``control`` as the array ``controls``; only CNOT has one."""
    none = F.array().cast("array<int>")
    return gates.withColumn("controls", F.when(F.col("kind") == "CNOT", F.array("control")).otherwise(none))


def _line_gates(lines: DataFrame, circuit: str, order: list[str], n: int, nets: str) -> DataFrame:
    target = F.pmod(F.col("l_partkey"), F.lit(n)).cast("int")
    code = F.pmod(F.col("l_linenumber") + F.col("l_partkey"), F.lit(12))
    # Named before the window, so that all that works by circuit needs no shuffle after it.
    lines = lines.withColumn("circuit_id", F.col(circuit).cast("long"))
    nth = F.row_number().over(Window.partitionBy("circuit_id").orderBy(*order)).cast("long")
    made = lines.select(
        "circuit_id", nth.alias("gate_no"), F.col("l_linenumber").cast("long").alias("net_no"),
        kind_of(code).alias("kind"), target.alias("target"),
        F.pmod(target + 1 + F.pmod(F.col("l_suppkey"), F.lit(n - 1)), F.lit(n)).cast("int").alias("control"),
        (F.pi() * F.col("l_quantity") / 25).alias("theta"),
    )
    return made if nets == "line" else made.withColumn("net_no", F.col("gate_no"))


def order_gates(spark: SparkSession, sf_dir: str, nets: str = "sequence") -> DataFrame:
    """One circuit of 5 qubits per order; nets are gates in sequence, or lines by number (with conflicts)."""
    order = ["l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
    return with_controls(_line_gates(table(spark, sf_dir, "lineitem"), "l_orderkey", order, 5, nets))


def supplier_gates(spark: SparkSession, sf_dir: str, n: int = 6) -> DataFrame:
    """One long circuit per supplier."""
    order = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"]
    return with_controls(_line_gates(table(spark, sf_dir, "lineitem"), "l_suppkey", order, n, "sequence"))


def part_gates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As :func:`order_gates` with kinds and angles from the gate library ``part``."""
    kinds = {"ECONOMY": "RX", "LARGE": "RY", "MEDIUM": "RZ", "PROMO": "H", "SMALL": "T", "STANDARD": "CNOT"}
    named = F.element_at(F.create_map(*[F.lit(x) for kv in kinds.items() for x in kv]), F.col("p_type"))
    library = table(spark, sf_dir, "part").select("p_partkey", named.alias("_kind"), "p_size")
    nth = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"))
    lines = table(spark, sf_dir, "lineitem").withColumn("gate_no", nth.cast("long"))
    met = lines.join(library, lines["l_partkey"] == library["p_partkey"])
    target = F.pmod(F.col("l_partkey"), F.lit(5)).cast("int")
    return with_controls(
        met.select(
            F.col("l_orderkey").alias("circuit_id"), "gate_no", F.col("gate_no").alias("net_no"), F.col("_kind").alias("kind"), target.alias("target"),
            F.pmod(target + 1 + F.pmod(F.col("l_suppkey"), F.lit(4)), F.lit(5)).cast("int").alias("control"), (F.pi() * F.col("p_size") / 25).alias("theta"),
        )
    )


def document_gates(spark: SparkSession, sf_dir: str, n: int = 6) -> DataFrame:
    """One circuit per document; all its words are the gates."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", " ")).alias("pos", "word"))
    length, first = F.length("word"), F.ascii(F.col("word"))
    target = F.pmod(first, F.lit(n)).cast("int")
    return with_controls(
        docs.select(
            F.col("doc_id").alias("circuit_id"), F.col("pos").cast("long").alias("gate_no"), F.col("pos").cast("long").alias("net_no"),
            kind_of(F.pmod(length + first, F.lit(12))).alias("kind"), target.alias("target"),
            F.pmod(target + 1 + F.pmod(length, F.lit(n - 1)), F.lit(n)).cast("int").alias("control"), (F.pi() * length / 6).alias("theta"),
        )
    )


def qubits_used(gates: DataFrame) -> Column:
    one = F.lit(1).cast("long")
    mask = F.call_function("shiftleft", one, F.col("target"))
    return F.aggregate("controls", mask, lambda m, q: m.bitwiseOR(F.call_function("shiftleft", one, q)))


def judge_nets(gates: DataFrame) -> DataFrame:
    """``gates`` with ``accepted``: in gate order, a gate is refused if an accepted one of its net uses a qubit of it.

    One shuffle by (circuit, net); a net has at most as many accepted gates as qubits, and the fold holds one mask.
    """
    fields = [c for c in gates.columns if c not in ("circuit_id", "net_no", "gate_no")]
    row = F.struct("gate_no", qubits_used(gates).alias("mask"), *fields)
    nets = gates.groupBy("circuit_id", "net_no").agg(F.array_sort(F.collect_list(row)).alias("rows"))
    empty = F.struct(F.lit(0).cast("long").alias("used"), F.array().cast("array<bigint>").alias("good"))
    fold = F.aggregate(
        "rows", empty,
        lambda s, x: F.when(
            s["used"].bitwiseAND(x["mask"]) == 0,
            F.struct(s["used"].bitwiseOR(x["mask"]).alias("used"), F.concat(s["good"], F.array(x["gate_no"])).alias("good")),
        ).otherwise(s),
    )
    return (
        nets.withColumn("good", fold["good"]).select("circuit_id", "net_no", "good", F.explode("rows").alias("x"))
        .select("circuit_id", "x.gate_no", "net_no", *[F.col(f"x.{c}") for c in fields], F.array_contains("good", F.col("x.gate_no")).alias("accepted"))
    )


def accepted_gates(gates: DataFrame) -> DataFrame:
    return judge_nets(gates).where("accepted").drop("accepted")


def net_log(gates: DataFrame) -> DataFrame:
    """Insert every gate, one iteration per net in order."""
    order = Window.partitionBy("circuit_id").orderBy("net_no", "gate_no")
    return gates.select(
        "circuit_id", F.row_number().over(order).cast("long").alias("seq"), F.dense_rank().over(Window.partitionBy("circuit_id").orderBy("net_no")).cast("long").alias("iter"),
        F.lit("insert").alias("op"), "net_no", "gate_no", "kind", "target", "controls", "theta",
    )


def level_rank(circuit: Column, level: Column) -> Column:
    """The integer hash that stands for a random choice of levels; equal in SQL."""
    return F.pmod(circuit * 48271 + level * 16807, F.lit(2147483647))


def insertion_log(gates: DataFrame, per_iter: int = 3) -> DataFrame:
    """Insert randomly ranked levels, ``per_iter`` of them an iteration."""
    nth = F.dense_rank().over(Window.partitionBy("circuit_id").orderBy(level_rank(F.col("circuit_id"), F.col("net_no")), "net_no"))
    made = gates.withColumn("nth", nth)
    order = Window.partitionBy("circuit_id").orderBy("nth", "gate_no")
    return made.select(
        "circuit_id", F.row_number().over(order).cast("long").alias("seq"), F.floor((F.col("nth") - 1) / per_iter).alias("iter"),
        F.lit("insert").alias("op"), "net_no", "gate_no", "kind", "target", "controls", "theta",
    )


def removal_log(gates: DataFrame, per_iter: int = 3) -> DataFrame:
    """Insert everything (iteration -1), then remove randomly ranked levels, ``per_iter`` of them an iteration."""
    rank = level_rank(F.col("circuit_id"), F.col("net_no"))
    nth = F.dense_rank().over(Window.partitionBy("circuit_id").orderBy(rank, "net_no"))
    made = gates.withColumn("put", F.row_number().over(Window.partitionBy("circuit_id").orderBy("net_no", "gate_no"))).withColumn("nth", nth)
    made = made.withColumn("gone", F.row_number().over(Window.partitionBy("circuit_id").orderBy("nth", "gate_no")))
    edit = lambda seq, it, op: F.struct(seq.cast("long").alias("seq"), it.cast("long").alias("iter"), F.lit(op).alias("op"))
    # Both edits of a gate come from its one row, so that the gates are shuffled once.
    both = F.array(edit(F.col("put"), F.lit(-1), "insert"), edit(F.col("gone") + F.lit(1_000_000), F.floor((F.col("nth") - 1) / per_iter), "remove"))
    return made.withColumn("x", F.explode(both)).select("circuit_id", "x.seq", "x.iter", "x.op", "net_no", "gate_no", "kind", "target", "controls", "theta")


def event_log(spark: SparkSession, sf_dir: str, n: int = 4) -> DataFrame:
    """Each user's events as edits of a circuit of 4 qubits, one iteration a day (see :func:`event_edits`)."""
    return event_edits(table(spark, sf_dir, "events"), n)


def event_edits(events: DataFrame, n: int = 4) -> DataFrame:
    """Events to an edit log.

    ``signup`` opens a net, ``click``/``view``/``purchase`` insert CNOT/H/RZ into the newest net, ``error``
    removes the newest live gate, which a count of open inserts from the end finds without a loop.  A gate
    gets a net of its own behind the opened one, so that no insert is refused.
    """
    k = F.get_json_object("props", "$.k").cast("int")
    kind = F.when(F.col("event_type") == "click", "CNOT").when(F.col("event_type") == "view", "H").when(F.col("event_type") == "purchase", "RZ")
    target = F.pmod(k, F.lit(n)).cast("int")
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    base = events.select(
        F.col("user_id").alias("circuit_id"), F.row_number().over(order).cast("long").alias("seq"), F.to_date("ts").alias("day"),
        F.when(kind.isNotNull(), 1).when(F.col("event_type") == "error", -1).otherwise(0).alias("d"), kind.alias("kind"), target.alias("target"),
        F.pmod(target + 1 + F.pmod(F.floor(k / n), F.lit(n - 1)), F.lit(n)).cast("int").alias("control"), (F.pi() * 2 * k / 100).alias("theta"),
    ).where("d <> 0")
    run = Window.partitionBy("circuit_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    # Depth of the stack of live gates; a removal at an empty stack leaves it empty.
    walk = base.withColumn("sum", F.sum("d").over(run)).withColumn("low", F.least(F.min("sum").over(run), F.lit(0)))
    walk = walk.withColumn("depth", F.col("sum") - F.col("low")).withColumn("before", F.coalesce(F.lag("depth").over(Window.partitionBy("circuit_id").orderBy("seq")), F.lit(0)))
    walk = walk.where("d = 1 or before > 0").withColumn("place", F.when(F.col("d") == 1, F.col("depth")).otherwise(F.col("before")))
    newest = Window.partitionBy("circuit_id", "place").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    walk = walk.withColumn("top", F.last(F.when(F.col("d") == 1, F.col("seq")), ignorenulls=True).over(newest))
    gate = F.when(F.col("d") == 1, F.col("seq")).otherwise(F.col("top"))
    day = F.dense_rank().over(Window.partitionBy("circuit_id").orderBy("day")).cast("long")
    made = walk.select(
        "circuit_id", "seq", day.alias("iter"), F.when(F.col("d") == 1, "insert").otherwise("remove").alias("op"), gate.alias("net_no"), gate.alias("gate_no"),
        F.when(F.col("d") == 1, F.col("kind")).alias("kind"), F.when(F.col("d") == 1, F.col("target")).alias("target"), "control",
        F.when(F.col("d") == 1, F.col("theta")).alias("theta"),
    )
    return with_controls(made).drop("control")


def levelize(gates: DataFrame, n: int) -> DataFrame:
    """``circuit_id, gate_no, level``: the earliest level of each gate with its qubits free, from 1.

    One shuffle by circuit; the fold carries one number per qubit.
    """
    rows = gates.groupBy("circuit_id").agg(F.array_sort(F.collect_list(F.struct("gate_no", F.concat(F.array("target"), "controls").alias("q")))).alias("rows"))
    zero = F.struct(F.array_repeat(F.lit(0), n).alias("busy"), F.array().cast("array<struct<gate_no:bigint,level:int>>").alias("out"))

    def step(s: Column, x: Column) -> Column:
        level = F.array_max(F.transform(x["q"], lambda q: F.element_at(s["busy"], q + 1))) + 1
        busy = F.transform(s["busy"], lambda b, i: F.when(F.array_contains(x["q"], i), level).otherwise(b))
        return F.struct(busy.alias("busy"), F.concat(s["out"], F.array(F.struct(x["gate_no"].alias("gate_no"), level.alias("level")))).alias("out"))

    return rows.select("circuit_id", F.explode(F.aggregate("rows", zero, step)["out"]).alias("x")).select("circuit_id", "x.gate_no", "x.level")
