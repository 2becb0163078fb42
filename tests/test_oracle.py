"""Every query that has SQL, against DuckDB on the smallest tables."""

from __future__ import annotations

import duckdb
import numpy as np
import pandas as pd
import pytest

from setvec.queries import QUERIES, SQL

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con():
    out = duckdb.connect()
    for t in TABLES:
        out.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return out


def plain(x):
    if x is None or x is pd.NA or (isinstance(x, float) and x != x):
        return None
    if isinstance(x, (float, np.floating)):
        near = round(float(x), 9)
        return int(near) if near.is_integer() else near
    return int(x) if isinstance(x, (int, np.integer)) and not isinstance(x, bool) else x


def rows(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(repr(tuple(map(plain, r))) for r in frame.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_equals_sql(spark, con, name):
    got, want = QUERIES[name](spark, SF).toPandas(), con.sql(SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_plans(spark):
    """Group limits below shuffles, filters at the scan, and no row-at-a-time Python."""
    plan = lambda name: QUERIES[name](spark, SF)._jdf.queryExecution().toString()
    near = plan("mips_dense_topk")
    assert "WindowGroupLimit" in near and "CartesianProduct" not in near and "BatchEvalPython" not in near
    assert "IsNotNull(embedding)" in near
    assert "ReadSchema: struct<doc_id:bigint,n_chars:bigint>" in plan("filtered_documents")
    for name in ("interval_events", "order_basket_similarity", "containment_truth"):
        assert "CartesianProduct" not in plan(name) and "BroadcastNestedLoopJoin" not in plan(name)
