"""Partitions of gates: which runs of blocks a gate's tasks write, as bit expressions.

A monomial gate's elementary operations are numbered by its free bits, that is by all index bits that it
neither fixes (controls, the set half of a one-sided scale) nor pairs (targets).  With blocks of 2**b
amplitudes, a task takes the b lowest free bits.  Free bits that are left below the highest paired bit
interleave their tasks, so they make sub-tasks of one partition; those above it make separate partitions
of equal size.  No amplitude and no task is ever enumerated.
"""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from incstate.functions.gates import classify, shape


class Pattern(NamedTuple):
    """A gate's partitions: ``count`` of them, each of ``tasks`` tasks from its lowest to highest amplitude."""

    fixed: int
    low_bits: int
    move: int
    upper: tuple[int, ...]
    tasks: int

    @property
    def count(self) -> int:
        return 1 << len(self.upper)

    def bounds(self, part: int, b: int) -> tuple[int, int]:
        """First and last block of a partition."""
        low = self.fixed + sum(((part >> k) & 1) << bit for k, bit in enumerate(self.upper))
        return low >> b, (low + self.low_bits + self.move) >> b


def pattern(kind: str, target: int, controls: tuple[int, ...], theta: float | None, n: int, b: int) -> Pattern | None:
    """The pattern of one gate on ``n`` qubits with blocks of ``2**b``; None if it does nothing."""
    form = shape(kind, theta)
    if form == "id":
        return None
    if form == "mix":
        return Pattern(0, (1 << b) - 1, 0, tuple(range(b, n)), 1)
    fixed, paired, top, move = sum(1 << c for c in controls), 0, -1, 0
    if form == "exchange":
        low, high = sorted((target, controls[0]))
        fixed = sum(1 << c for c in controls[1:]) | 1 << low
        paired, top, move = 1 << high, high, (1 << high) - (1 << low)
    elif form == "swap":
        paired, top, move = 1 << target, target, 1 << target
    elif form == "one":
        fixed |= 1 << target
    free = [q for q in range(n) if not (fixed | paired) >> q & 1]
    inside, rest = free[:b], free[b:]
    fused = [q for q in rest if q < top]
    return Pattern(fixed, sum(1 << q for q in inside + fused), move, tuple(q for q in rest if q > top), 1 << len(fused))


def _bit(q: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), q.cast("int"))


def _mask(qubits: Column) -> Column:
    return F.aggregate(qubits, F.lit(0).cast("long"), lambda m, q: m.bitwiseOR(_bit(q)))


def _pattern_columns(gates: DataFrame, n: int, b: int) -> DataFrame:
    """``gates`` (classified, not ``id``) with ``fixed, low_bits, move, upper, n_tasks``."""
    target, controls, form = F.col("target"), F.coalesce(F.col("controls"), F.array().cast("array<int>")), F.col("shape")
    other = F.element_at(controls, 1)
    low, high = F.least(target, other), F.greatest(target, other)
    rest = F.when(form == "exchange", F.slice(controls, 2, 62)).otherwise(controls)
    zero = F.lit(0).cast("long")
    fixed = _mask(rest).bitwiseOR(F.when(form == "exchange", _bit(low)).when(form == "one", _bit(target)).otherwise(zero))
    paired = F.when(form == "exchange", _bit(high)).when(form == "swap", _bit(target)).otherwise(zero)
    top = F.when(form == "exchange", high).when(form == "swap", target).otherwise(F.lit(-1))
    move = F.when(form == "exchange", _bit(high) - _bit(low)).when(form == "swap", _bit(target)).otherwise(zero)
    out = gates.withColumn("fixed", F.when(form == "mix", zero).otherwise(fixed)).withColumn("move", move).withColumn("top", top)
    used = F.col("fixed").bitwiseOR(F.when(form == "mix", zero).otherwise(paired))
    free = F.filter(F.sequence(F.lit(0), F.lit(n - 1)), lambda q: used.bitwiseAND(_bit(q)) == 0)
    out = out.withColumn("free", free)
    over = F.slice("free", b + 1, n + 1)
    out = out.withColumn("upper", F.filter(over, lambda q: q > F.col("top")))
    fused = F.filter(over, lambda q: q < F.col("top"))
    inside = F.slice("free", 1, b) if b else F.array().cast("array<int>")
    return (
        out.withColumn("low_bits", _mask(inside) + _mask(fused))
        .withColumn("n_tasks", _bit(F.size(fused)))
        .drop("free", "top")
    )


def gate_patterns(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """``gates`` with shape, mode and pattern; gates that do nothing go.  ``span`` is blocks per partition."""
    b = log2(block_size, n)
    seen = classify(gates) if "shape" not in gates.columns else gates
    out = _pattern_columns(seen.where("mode <> 'id'"), n, b)
    last = F.col("fixed") + F.col("low_bits") + F.col("move")
    span = F.shiftright(last, b) - F.shiftright(F.col("fixed"), b) + 1
    return out.withColumn("span", span).withColumn("n_parts", _bit(F.size("upper")))


def expand(patterns: DataFrame, n: int, block_size: int) -> DataFrame:
    """``patterns`` to one row per partition with ``part_no, lo_block, hi_block``."""
    b = log2(block_size, n)
    low = F.col("fixed") + F.aggregate(
        F.transform("upper", lambda q, k: F.struct(q.alias("q"), k.alias("k"))),
        F.lit(0).cast("long"),
        lambda s, x: s + F.call_function("shiftright", F.col("part_no"), x["k"]).bitwiseAND(1) * _bit(x["q"]),
    )
    return (
        patterns.withColumn("part_no", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_parts") - 1)))
        .withColumn("_low", low)
        .withColumn("lo_block", F.shiftright("_low", b))
        .withColumn("hi_block", F.shiftright(F.col("_low") + F.col("low_bits") + F.col("move"), b))
        .withColumn("part_no", F.col("part_no").cast("int"))
        .drop("_low")
    )


def derive_partitions(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """Partitions of gates one by one: ``circuit_id, gate_no, part_no, lo_block, hi_block, n_tasks``."""
    return expand(gate_patterns(gates, n, block_size), n, block_size).select(
        "circuit_id", "gate_no", "part_no", "lo_block", "hi_block", "n_tasks"
    )


def enumerate_partitions(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """As :func:`derive_partitions` by walking every gate's operations, ``2**n`` rows a gate.

    Operations in index order are dealt to tasks of ``block_size``; tasks whose spans overlap are one partition.
    The truth that the closed form is held against, for small vectors.
    """
    b = log2(block_size, n)
    seen = (classify(gates) if "shape" not in gates.columns else gates).where("mode <> 'id'")
    form, target, i = F.col("shape"), F.col("target"), F.col("i")
    controls = F.coalesce(F.col("controls"), F.array().cast("array<int>"))
    other = F.element_at(controls, 1)
    held = _mask(F.when(form == "exchange", F.slice(controls, 2, 62)).otherwise(controls))
    pair = _bit(target).bitwiseOR(_bit(other))
    acts = (
        F.when(form == "swap", i.bitwiseAND(_bit(target)) == 0).when(form == "one", i.bitwiseAND(_bit(target)) != 0)
        .when(form == "exchange", i.bitwiseAND(pair) == _bit(F.least(target, other))).otherwise(True)
    )
    end = F.when(form == "swap", i.bitwiseOR(_bit(target))).when(form == "exchange", i.bitwiseXOR(pair)).otherwise(i)
    gate = ["circuit_id", "gate_no"]
    ops = (
        seen.where("shape <> 'mix'").withColumn("held", held).withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit((1 << n) - 1).cast("long"))))
        .where((i.bitwiseAND(F.col("held")) == F.col("held")) & acts)
        .select(*gate, "i", end.alias("end"))
    )
    nth = F.row_number().over(Window.partitionBy(*gate).orderBy("i")) - 1
    tasks = (
        ops.withColumn("task", F.floor(nth / F.lit(1 << b))).groupBy(*gate, "task")
        .agg(F.shiftright(F.min("i"), b).alias("lo"), F.shiftright(F.max(F.greatest("i", "end")), b).alias("hi"))
    )
    order = Window.partitionBy(*gate).orderBy("task")
    ahead = F.max("hi").over(order.rowsBetween(Window.unboundedPreceding, -1))
    isle = tasks.withColumn("new", (ahead.isNull() | (F.col("lo") > ahead)).cast("int")).withColumn("part_no", (F.sum("new").over(order) - 1).cast("int"))
    mono = isle.groupBy(*gate, "part_no").agg(F.min("lo").alias("lo_block"), F.max("hi").alias("hi_block"), F.count("*").alias("n_tasks"))
    k = F.col("lo_block")
    mix = seen.where("shape = 'mix'").select(*gate, F.explode(F.sequence(F.lit(0).cast("long"), F.lit((1 << (n - b)) - 1).cast("long"))).alias("lo_block"))
    return mono.unionByName(mix.select(*gate, k.cast("int").alias("part_no"), "lo_block", k.alias("hi_block"), F.lit(1).cast("long").alias("n_tasks")))


def log2(block_size: int, n: int) -> int:
    """Bits of a block; a block is no larger than the vector."""
    if block_size < 1 or block_size & (block_size - 1):
        raise ValueError("a block size is a power of two")
    return min(block_size.bit_length() - 1, n)
