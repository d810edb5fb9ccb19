"""Families whose circuits come from a table: equal to SQL, and a scan of that table is in the plan."""

from __future__ import annotations

import duckdb
import pytest

from incstate.workloads import measures  # noqa: F401
from incstate.workloads.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name, source", [("family_ghz", "orders"), ("family_coin", "lineitem"), ("family_counts", "lineitem")])
def test_reads_its_table(spark, data, name, source):
    duck = duckdb.connect()
    duck.execute(f"create view {source} as select * from '{data}/{source}.parquet'")
    df = QUERIES[name](spark, data)
    assert any(f"{source}.parquet" in f for f in df.inputFiles())
    ours, theirs = df.toPandas(), duck.execute(ORACLES[name]).df()
    names = sorted(ours.columns)
    assert names == sorted(theirs.columns) and len(ours) > 20
    key = lambda d: sorted(map(tuple, d[names].astype(str).values.tolist()))
    assert key(ours) == key(theirs)
    assert {c: str(t) for c, t in ours.dtypes.items()} == {c: str(t) for c, t in theirs.dtypes.items()}
