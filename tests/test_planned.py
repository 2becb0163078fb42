"""The planner's ways give the dense scan's lists, whatever the sizes of files and batches."""

from __future__ import annotations

import numpy as np
import pytest

from setvec.operators import encode, search
from setvec.plans import planner
from setvec.plans.params import EncodeParams
from setvec.plans.retriever import Retriever

DIM = 16
PARAMS = EncodeParams(DIM, 3, 8, 8)


@pytest.fixture(scope="module")
def bags(spark):
    rng = np.random.default_rng(7)
    rows = lambda n, m: [(i, m, rng.normal(size=(m, DIM)).astype("<f4").tobytes()) for i in range(n)]
    ddl = "bag_id bigint, n int, vecs binary"
    return spark.createDataFrame(rows(20, 4), ddl), spark.createDataFrame(rows(2000, 8), ddl)


def lists(df):
    return sorted((r["query_id"], r["rank"], r["doc_id"]) for r in df.collect())


@pytest.mark.parametrize("tasks", [1, 16])
def test_progressive_scan_is_dense(bags, tasks):
    q, d = encode.encode_queries(bags[0], PARAMS), encode.encode_documents(bags[1], PARAMS)
    want = lists(search.mips_dense(q, d, 5, PARAMS))
    for first in (1, 4, 7):
        assert lists(search.mips_progressive(q, d.coalesce(tasks), 5, PARAMS, first, 5)) == want


def test_auto_takes_no_lossy_index(bags, monkeypatch):
    monkeypatch.setattr(planner, "SCAN_NUMBERS", 1)
    want = lists(Retriever(PARAMS, "dense").fit(bags[1]).search(bags[0], 5, 20, tau=None))
    way = Retriever(PARAMS, "auto").fit(bags[1], n_queries=20)
    assert way.choice.index == "ivf" and way.way in ("dense", "progressive", "sparse")
    assert lists(way.search(bags[0], 5, 20, tau=None)) == want
