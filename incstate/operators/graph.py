"""Slots, partition graphs, waves and their text form, for any number of circuits at once.

Slots: the superposition gates of a net share its first slot; every other gate has one of its own, those
of narrow partitions first.  Links: a partition depends on the latest earlier writer of each of its
blocks, which one window over (circuit, block) gives; a superposition slot reads all blocks through a
synchronisation node (part ``SYNC``) on which its one-block partitions depend.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from incstate.operators.partition import expand, gate_patterns
from incstate.schema import SYNC


def slot_patterns(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """One row per gate with its pattern and ``slot_no`` (from 0 in each circuit)."""
    made = gate_patterns(gates, n, block_size).withColumn("rank", F.when(F.col("mode") == "sup", 0).otherwise(1))
    key = F.struct("net_no", "rank", F.when(F.col("rank") == 0, 0).otherwise(F.col("span")), F.when(F.col("rank") == 0, 0).otherwise(F.col("gate_no")))
    order = Window.partitionBy("circuit_id").orderBy("slot_key")
    return made.withColumn("slot_key", key).withColumn("slot_no", (F.dense_rank().over(order) - 1).cast("int"))


def layout_slots(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """``circuit_id, slot_no, net_no, mode, gate_nos, span``."""
    return (
        slot_patterns(gates, n, block_size)
        .groupBy("circuit_id", "slot_no", "net_no", "mode")
        .agg(F.array_sort(F.collect_list("gate_no")).alias("gate_nos"), F.max("span").alias("span"))
        .select("circuit_id", "slot_no", "net_no", "mode", "gate_nos", "span")
    )


def slot_partitions(gates: DataFrame, n: int, block_size: int) -> DataFrame:
    """``circuit_id, slot_no, net_no, mode, gate_no, part_no, lo_block, hi_block, n_tasks``; gate_no is a shared slot's first."""
    one = slot_patterns(gates, n, block_size)
    first = Window.partitionBy("circuit_id", "slot_no").orderBy("gate_no")
    one = one.withColumn("_nth", F.row_number().over(first)).where("_nth = 1")
    return expand(one, n, block_size).select(
        "circuit_id", "slot_no", "net_no", "mode", "gate_no", "part_no", "lo_block", "hi_block", "n_tasks"
    )


def written_blocks(parts: DataFrame) -> DataFrame:
    """One row per block of each partition."""
    return parts.withColumn("block_id", F.explode(F.sequence("lo_block", "hi_block")))


def link_partitions(parts: DataFrame) -> DataFrame:
    """Edges ``circuit_id, src_slot, src_part, dst_slot, dst_part`` to the closest earlier writers."""
    before = Window.partitionBy("circuit_id", "block_id").orderBy("slot_no")
    seen = written_blocks(parts).withColumn("src", F.lag(F.struct("slot_no", "part_no")).over(before))
    reader = F.when(F.col("mode") == "sup", F.lit(SYNC)).otherwise(F.col("part_no"))
    data = seen.where("src is not null").select(
        "circuit_id", F.col("src.slot_no").alias("src_slot"), F.col("src.part_no").alias("src_part"),
        F.col("slot_no").alias("dst_slot"), reader.alias("dst_part"),
    ).distinct()
    sync = parts.where("mode = 'sup'").select(
        "circuit_id", F.col("slot_no").alias("src_slot"), F.lit(SYNC).alias("src_part"),
        F.col("slot_no").alias("dst_slot"), F.col("part_no").alias("dst_part"),
    )
    return data.unionByName(sync)


def link_by_intersection(parts: DataFrame) -> DataFrame:
    """The same data edges by range intersection: every overlapping earlier pair, minus the blocks that a
    closer partition covers.  A check for small graphs."""
    a, b = parts.alias("a"), parts.alias("b")
    meet = (F.col("a.circuit_id") == F.col("b.circuit_id")) & (F.col("a.slot_no") < F.col("b.slot_no"))
    meet &= (F.col("a.lo_block") <= F.col("b.hi_block")) & (F.col("b.lo_block") <= F.col("a.hi_block"))
    pairs = a.join(b, meet).select(
        "b.circuit_id", F.col("a.slot_no").alias("src_slot"), F.col("a.part_no").alias("src_part"), F.col("b.slot_no").alias("dst_slot"),
        F.col("b.part_no").alias("part"), F.col("b.mode").alias("mode"),
        F.explode(F.sequence(F.greatest("a.lo_block", "b.lo_block"), F.least("a.hi_block", "b.hi_block"))).alias("block_id"),
    )
    close = Window.partitionBy("circuit_id", "dst_slot", "part", "block_id").orderBy(F.col("src_slot").desc())
    return (
        pairs.withColumn("nth", F.row_number().over(close)).where("nth = 1")
        .select("circuit_id", "src_slot", "src_part", "dst_slot", F.when(F.col("mode") == "sup", SYNC).otherwise(F.col("part")).alias("dst_part"))
        .distinct()
    )


_EDGE = T.ArrayType(T.StructType().add("src_slot", "integer").add("src_part", "integer").add("dst_slot", "integer").add("dst_part", "integer"))


def list_rows(lists: pa.Array) -> tuple[np.ndarray, pa.StructArray]:
    """The rows of lists, and which list each is of; a null list has none."""
    lists = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
    return np.repeat(np.arange(len(lists)), pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False)), lists.flatten()


@F.arrow_udf(_EDGE)
def _relinked(parts: pa.Array, edges: pa.Array, blocks: pa.Array) -> pa.Array:
    """:func:`relink` for all circuits of a batch at once."""
    number = lambda rows, k: rows.field(k).to_numpy(zero_copy_only=False).astype(np.int64)
    of, p = list_rows(parts)
    slot, part, sup, lo, hi = (number(p, k) for k in ("slot_no", "part_no", "sup", "lo_block", "hi_block"))
    of_edge, e = list_rows(edges)
    src_slot, src_part, dst_slot, dst_part = (number(e, k) for k in ("src_slot", "src_part", "dst_slot", "dst_part"))
    of_block, touched = list_rows(blocks)
    touched = touched.to_numpy(zero_copy_only=False).astype(np.int64)
    wide = max(hi.max(initial=0), touched.max(initial=0)) + 1
    deep, most = max(slot.max(initial=0), dst_slot.max(initial=0)) + 1, max(part.max(initial=0), dst_part.max(initial=0)) + 2
    reader = np.where(sup == 1, SYNC, part)
    target = (of * deep + slot) * most + reader + 1
    count = hi - lo + 1
    row = np.repeat(np.arange(len(of)), count)
    block = of[row] * wide + np.arange(len(row)) - np.repeat(np.cumsum(count) - count - lo, count)
    hit = np.isin(block, of_block * wide + touched)
    changed = np.unique(target[row[hit]])
    again = np.isin(target, changed)
    local = np.flatnonzero(np.isin(block, block[again[row]]))
    local = local[np.lexsort((slot[row[local]], block[local]))]
    follows = np.flatnonzero((np.diff(block[local]) == 0) & again[row[local[1:]]]) + 1
    a, z = row[local[follows - 1]], row[local[follows]]
    order = np.lexsort((part[a], slot[a], target[z]))
    a, z = a[order], z[order]
    first = np.ones(len(a), bool)
    first[1:] = (np.diff(target[z]) != 0) | (np.diff(slot[a]) != 0) | (np.diff(part[a]) != 0)
    a, z = a[first], z[first]
    into = (of_edge * deep + dst_slot) * most + dst_part + 1
    kept = np.isin(into, target) & ~np.isin(into, changed)
    own = np.flatnonzero(sup == 1)
    made = [np.concatenate(x) for x in zip(
        (of[z], slot[a], part[a], slot[z], reader[z]),
        (of_edge[kept], src_slot[kept], src_part[kept], dst_slot[kept], dst_part[kept]),
        (of[own], slot[own], np.full(len(own), SYNC), slot[own], part[own]),
    )]
    made = [x[np.argsort(made[0], kind="stable")] for x in made]
    return node_lists(len(parts), made[0], src_slot=made[1], src_part=made[2], dst_slot=made[3], dst_part=made[4])


def relink(parts: DataFrame, edges: DataFrame, blocks: DataFrame) -> DataFrame:
    """Edges after an edit that touched ``blocks(circuit_id, block_id)``.

    Slots keep their numbers.  Partitions over a touched block are linked anew (a superposition slot as a
    whole, since all its partitions read through one node), and only the blocks that these cover take part
    in it; the other edges stay where their target does.  Everything meets by circuit alone, so inputs that are
    dealt by circuit are not shuffled again.
    """
    part = F.struct("slot_no", "part_no", (F.col("mode") == "sup").cast("int").alias("sup"), "lo_block", "hi_block")
    p = parts.groupBy("circuit_id").agg(F.collect_list(part).alias("p"))
    e = edges.where(F.col("src_part") != SYNC).groupBy("circuit_id").agg(F.collect_list(F.struct("src_slot", "src_part", "dst_slot", "dst_part")).alias("e"))
    b = blocks.groupBy("circuit_id").agg(F.collect_set("block_id").alias("b"))
    met = p.join(e, "circuit_id", "left").join(b, "circuit_id", "left")
    return met.select("circuit_id", F.explode(_relinked("p", "e", "b")).alias("x")).select("circuit_id", "x.*")


def changed_blocks(parts: DataFrame, old_parts: DataFrame) -> DataFrame:
    """``circuit_id, block_id`` that slots cover which only one side has, of circuits that have ``parts``."""
    spans = lambda of, name: of.groupBy("circuit_id").agg(
        F.collect_list(F.struct("slot_no", "lo_block", "hi_block")).alias(name), F.collect_set("slot_no").alias(f"{name}_slots")
    )
    met = spans(parts, "new").join(spans(old_parts, "old"), "circuit_id", "left")
    none = lambda name: F.coalesce(name, F.slice("new" if name == "old" else "new_slots", 1, 0))
    met = met.withColumn("old", none("old")).withColumn("old_slots", none("old_slots"))
    met = met.withColumn("only", F.concat(F.array_except("new_slots", "old_slots"), F.array_except("old_slots", "new_slots")))
    some = F.filter(F.concat("new", "old"), lambda x: F.array_contains("only", x["slot_no"]))
    blocks = F.array_distinct(F.flatten(F.transform(some, lambda x: F.sequence(x["lo_block"], x["hi_block"]))))
    return met.select("circuit_id", F.explode(blocks).alias("block_id"))


def packed_edges(edges: pa.Array, *more: tuple[np.ndarray, np.ndarray, np.ndarray]) -> tuple[np.ndarray, ...]:
    """Lists of edges, a list per circuit, as arrays over the whole batch.

    Returns ``(node, circuit, slot, part, src, dst, steps)``: the batch's distinct nodes by circuit, slot and
    part, each edge's ends as node numbers in the order in which ends are settled (by target slot, a slot's
    sync node before its partitions), and the bounds of the steps in that order.  ``more`` are further nodes,
    as (circuit, slot, part).
    """
    edges = edges.combine_chunks() if isinstance(edges, pa.ChunkedArray) else edges
    of = np.repeat(np.arange(len(edges)), pc.fill_null(pc.list_value_length(edges), 0).to_numpy(zero_copy_only=False))
    rows = edges.flatten()
    src_slot, src_part, dst_slot, dst_part = (rows.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in ("src_slot", "src_part", "dst_slot", "dst_part"))
    circuit, slot, part = (np.concatenate(x) for x in zip((of, src_slot, src_part), (of, dst_slot, dst_part), *more))
    wide, deep = part.max(initial=0) + 2, slot.max(initial=0) + 1
    code, number = np.unique((circuit * deep + slot) * wide + part + 1, return_inverse=True)
    step = 2 * dst_slot + (dst_part != SYNC)
    order = np.argsort(step, kind="stable")
    cuts = np.concatenate(([0], np.flatnonzero(np.diff(step[order])) + 1, [len(order)])) if len(order) else np.zeros(1, np.int64)
    src, dst = number[: len(of)][order], number[len(of) : 2 * len(of)][order]
    return number[2 * len(of) :], code // wide // deep, code // wide % deep, code % wide - 1, src, dst, cuts


_NODE = T.ArrayType(T.StructType().add("slot_no", "integer").add("part_no", "integer").add("wave", "integer"))


def node_lists(n: int, circuit: np.ndarray, **columns: np.ndarray) -> pa.Array:
    """Rows (in circuit order) as one list of structs for each of ``n`` circuits."""
    ends = np.concatenate(([0], np.cumsum(np.bincount(circuit, minlength=n))))
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.StructArray.from_arrays([pa.array(c, pa.int32()) for c in columns.values()], names=list(columns)))


@F.arrow_udf(_NODE)
def _waves(edges: pa.Array) -> pa.Array:
    """Longest-path wave of every node, for all circuits of a batch at once, slot by slot."""
    _, circuit, slot, part, src, dst, steps = packed_edges(edges)
    wave = np.zeros(len(circuit), np.int64)
    for a, b in zip(steps, steps[1:]):
        np.maximum.at(wave, dst[a:b], wave[src[a:b]] + 1)
    return node_lists(len(edges), circuit, slot_no=slot, part_no=part, wave=wave)


def task_waves(parts: DataFrame, edges: DataFrame) -> DataFrame:
    """``circuit_id, slot_no, part_no, wave``: nodes of a wave can run together.  One shuffle by circuit."""
    packed = edges.groupBy("circuit_id").agg(F.collect_list(F.struct("src_slot", "src_part", "dst_slot", "dst_part")).alias("e"))
    linked = packed.select("circuit_id", F.explode(_waves("e")).alias("x")).select("circuit_id", "x.*")
    nodes = parts.select("circuit_id", "slot_no", "part_no").unionByName(
        parts.where("mode = 'sup'").select("circuit_id", "slot_no", F.lit(SYNC).alias("part_no")).distinct()
    )
    return nodes.join(linked, ["circuit_id", "slot_no", "part_no"], "left").select(
        "circuit_id", "slot_no", "part_no", F.coalesce("wave", F.lit(0)).alias("wave")
    )


def graph_stats(parts: DataFrame, edges: DataFrame) -> DataFrame:
    """Per circuit: partitions, static tasks (with sync nodes and the output), sub-tasks and edges."""
    p = parts.groupBy("circuit_id").agg(
        F.count("*").alias("partitions"),
        (F.count("*") + F.countDistinct(F.when(F.col("mode") == "sup", F.col("slot_no"))) + 1).alias("static_tasks"),
        F.sum(F.when(F.col("n_tasks") > 1, F.col("n_tasks")).otherwise(0)).cast("long").alias("sub_tasks"),
        F.sum(F.col("hi_block") - F.col("lo_block") + 1).cast("long").alias("written_blocks"),
    )
    e = edges.groupBy("circuit_id").agg(F.count("*").alias("edges"))
    return p.join(e, "circuit_id", "left").withColumn("edges", F.coalesce("edges", F.lit(0).cast("long")))


def graph_dot(edges: DataFrame) -> DataFrame:
    """``circuit_id, dot``: each circuit's graph in DOT, edges in order."""
    name = lambda s, p: F.when(F.col(p) == SYNC, F.format_string("sync_%d", F.col(s))).otherwise(F.format_string("s%d_p%d", F.col(s), F.col(p)))
    line = F.concat(F.lit("  "), name("src_slot", "src_part"), F.lit(" -> "), name("dst_slot", "dst_part"), F.lit(";"))
    rows = edges.groupBy("circuit_id").agg(
        F.array_sort(F.collect_list(F.struct("src_slot", "src_part", "dst_slot", "dst_part", line.alias("line")))).alias("rows")
    )
    return rows.select(
        "circuit_id", F.concat(F.lit("digraph partitions {\n"), F.array_join(F.col("rows.line"), "\n"), F.lit("\n}")).alias("dot")
    )
