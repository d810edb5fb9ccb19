"""Edits of many graphs meet by circuit: relinking, frontiers and hops against plain Python, and no other shuffle."""

from __future__ import annotations

import re

import duckdb
import pytest

from incstate.operators import graph, update
from incstate.workloads import queries
from incstate.workloads.queries import ORACLES, QUERIES


def exchanges(df):
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {re.sub(r"#\d+L?", "", keys) for keys in re.findall(r"Exchange hashpartitioning\((.*), \d+\)", plan)}


@pytest.mark.parametrize("name", ["affected_by_hops", "frontiers", "relink_after_edit"])
def test_equal_to_sql_and_dealt_by_circuit_alone(spark, data, name):
    duck = duckdb.connect()
    duck.execute(f"create view lineitem as select * from '{data}/lineitem.parquet'")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        df = QUERIES[name](spark, data)
        assert exchanges(df) == {"circuit_id"}
        ours = df.toPandas()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    theirs = duck.execute(ORACLES[name]).df()
    names = sorted(ours.columns)
    assert names == sorted(theirs.columns)
    key = lambda d: sorted(map(tuple, d[names].astype(str).values.tolist()))
    assert key(ours) == key(theirs)
    plan = df._jdf.queryExecution().analyzed().toString()
    assert "LogicalRDD" not in plan, "nothing is stored on the way"


def test_hops_are_shortest_distances(spark, data):
    _, links, start = queries._edit_graphs(spark, data, True, True)
    out, edges = {}, {}
    for e in links.collect():
        edges.setdefault((e.circuit_id, e.src_slot, e.src_part), []).append((e.circuit_id, e.dst_slot, e.dst_part))
    delta, hop = {(r.circuit_id, r.slot_no, r.part_no) for r in start.collect()}, 0
    while delta:
        out |= dict.fromkeys(delta, hop)
        hop += 1
        delta = {z for a in delta for z in edges.get(a, ())} - set(out)
    got = {(r.circuit_id, r.slot_no, r.part_no): r.hops for r in update.affected_by_hops(links, start).collect()}
    assert got == {k: h for k, h in out.items() if k[2] != -1} and max(got.values()) > 3


def test_relink_of_a_circuit_that_is_new(spark):
    """No old edges and no old parts: all is linked anew."""
    parts = spark.createDataFrame(
        [(1, 0, 0, "mono", 0, 1), (1, 1, 0, "mono", 1, 1), (1, 2, 0, "sup", 0, 0), (1, 2, 1, "sup", 1, 1), (2, 0, 0, "mono", 0, 0)],
        "circuit_id long, slot_no int, part_no int, mode string, lo_block long, hi_block long",
    )
    none = parts.where("slot_no > 9")
    edges = graph.link_partitions(parts)
    got = graph.relink(parts, edges.where("false"), graph.changed_blocks(parts, none))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, edges.select(got.columns).collect()))
