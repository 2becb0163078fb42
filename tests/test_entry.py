from __future__ import annotations

import __spark_entry__ as e


def test_entry(spark):
    df = e.entry(spark)
    assert df.columns == ["query_id", "rank", "doc_id", "score"] and df.count() > 0


def test_names_match():
    assert set(e.oracle_sql()) <= set(e.queries()) and len(e.queries()) > 60


def test_core_stands_without_the_pipeline_operators(monkeypatch):
    monkeypatch.setattr(e, "_has", lambda name: False)
    assert "pipeline" not in e.queries() and not any(n.startswith("op1_") for n in e.queries())
    assert not any(n.startswith("op") and n[2].isdigit() for n in e.oracle_sql())
