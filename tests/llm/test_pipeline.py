"""The pipeline, stage by stage, against plain Python on a small table."""

from __future__ import annotations

import numpy as np
import pytest

import corpus_pipeline
from setvec.llm.tokens import coder

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    base = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    extra = spark.createDataFrame([(9001, None, None, None, None), (9002, "", "en", "src1", 0), (9003, "123 !!", "en", "src1", 6)], DOCS)
    docs, out = base.union(extra), []
    folder = tmp_path_factory.mktemp("stages")
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, "").write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        out.append(docs.toPandas())
    return base.toPandas(), out


def test_stages_keep_columns_and_clean_documents(stages):
    base, (told, single, clean, mixed, _) = stages
    assert told.doc_id.tolist().sort() == base.doc_id.tolist().sort() and len(told) == len(base)
    for frame in (told, single, clean, mixed):
        assert frame.columns.tolist() == base.columns.tolist()
    assert set(single.doc_id) == set(clean.doc_id) and len(single) < len(told)
    whole = dict(zip(base.doc_id, base.text, strict=True))
    changed = [i for i, x in zip(clean.doc_id, clean.text, strict=True) if whole[i] != x]
    assert all("<assign>" in x or "<hex>" in x for i, x in zip(clean.doc_id, clean.text, strict=True) if i in changed)
    assert (clean.n_chars == clean.text.str.len()).all()


def test_one_document_of_each_group_stays(stages):
    base, (_, single, *_) = stages
    by_text = base.groupby("text").doc_id.min()
    assert set(single.doc_id) <= set(by_text) and single.text.is_unique


def test_packing_holds_every_copy(stages):
    _, (*_, mixed, packed) = stages
    want = sum(len(np.frombuffer(x, "<u4")) + 1 for x in coder().encode(mixed.text.tolist()))
    assert packed.length.sum() == want and packed.groupby("sequence_id").length.sum().max() <= 2048
    assert mixed.groupby("doc_id").size().max() <= 3
    first = packed[packed.start == 0].groupby("doc_id").size()
    assert (first == mixed.groupby("doc_id").size()).all()


def test_run(spark):
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001").count() > 0


def test_empty(spark):
    docs = spark.createDataFrame([], DOCS)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, "")
        assert docs.count() == 0 and docs.columns == [c.split()[0] for c in DOCS.split(", ")]
    assert corpus_pipeline.pack(spark, docs, "").count() == 0
