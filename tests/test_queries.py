"""Registered queries against their SQL on the smallest tables, and the driver's contract."""

from __future__ import annotations

import duckdb
import pytest

from incstate.workloads import measures, suite, surface  # noqa: F401
from incstate.workloads.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Quick ones; the driver compares all.
CHECKED = [
    "encode_embeddings", "circuit_from_orders", "net_accept", "partitions_orders", "slots", "edges", "graph_waves", "affected_mixed", "relink_after_edit", "partitions_enum", "partitions_closed", "full_orders",
    "full_embeddings", "mono_swap_cz_ccx", "super_h_net", "inc_insert", "inc_remove", "inc_mixed", "inc_report_counts", "circuit_from_text", "join_lateral_terms", "udtf_parse_gates", "full_documents", "cow_saving", "levelize", "sample_shots",
    "worked_after_insert", "worked_affected", "family_adder", "family_multiplier", "family_factoring", "family_satisfying", "family_order", "stats_cube", "join_interval", "join_asof", "win_running_max", "stream_tumbling", "udtf_partition_ranges",
]


@pytest.fixture(scope="module")
def duck(data):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{data}/{t}.parquet'")
    return c


def rows(frame, names):
    return sorted(map(tuple, frame[names].astype(object).where(frame[names].notna(), None).astype(str).values.tolist()))


@pytest.mark.parametrize("name", CHECKED)
def test_equals_sql(spark, duck, data, name):
    ours, theirs = QUERIES[name](spark, data).toPandas(), duck.execute(ORACLES[name]).df()
    names = sorted(ours.columns)
    assert names == sorted(theirs.columns)
    assert rows(ours, names) == rows(theirs, names)


def test_contract(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() > 0


def test_rows_only_queries(spark, data):
    mixed = QUERIES["inc_mixed_counts"](spark, data).toPandas()
    assert (mixed.written_blocks <= mixed.total_blocks).all() and len(mixed)
    near = QUERIES["approx_basis_distinct"](spark, data).toPandas()
    assert ((near.near - near.exact).abs() <= 0.1 * near.exact + 1).all()
    q = QUERIES["approx_prob_quantile"](spark, data).toPandas()
    assert ((q["median"] - q.exact).abs() < 0.02).all()
    live = QUERIES["stream_stateful_circuit"](spark, data).toPandas()
    assert (live.live_gates <= live.edits).all() and len(live)


def test_stateful_stream_equals_batch_fold(spark, data):
    from incstate.workloads import circuits

    log = circuits.event_log(spark, data).toPandas()
    live = {u: (g.op == "insert").sum() - (g.op == "remove").sum() for u, g in log.groupby("circuit_id")}
    for r in QUERIES["stream_stateful_circuit"](spark, data).collect():
        assert live[r.circuit_id] == r.live_gates


def test_scans_are_pruned(spark, data):
    plan = QUERIES["circuit_from_orders"](spark, data)._jdf.queryExecution().executedPlan().toString()
    assert "l_shipdate" not in plan and "l_extendedprice" in plan
    plan = QUERIES["mono_permute"](spark, data)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
