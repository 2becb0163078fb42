"""The sweeps on the smallest tables: shapes and the directions that are expected of them."""

from __future__ import annotations

import numpy as np
import pytest

from setvec import experiments as X
from setvec import workloads as WL

SF = "/root/testdata/sf0.001"


def test_grid(spark):
    rows = X.grid_recall(spark, SF).toPandas()
    assert len(rows) == 300 and (rows.width == rows.reps * 2**rows.bits * rows.proj).all()
    wide, slim = rows[(rows.n == 1) & (rows.width >= 5120)].recall.mean(), rows[(rows.n == 1) & (rows.width < 500)].recall.mean()
    assert wide > slim + 0.2
    per_reps = rows[rows.n == 1].groupby("reps").recall.mean()
    assert per_reps[20] > per_reps[5] > per_reps[1]


def test_grid_equals_single_settings(spark):
    rows = X.grid_recall(spark, SF).where("reps = 20 and bits = 3 and proj = 8").toPandas().set_index("n").recall
    want = WL.recall_by_width(spark, SF, widths=(1280,)).toPandas().set_index("n").recall
    assert rows.to_dict() == want.to_dict()


def test_centres_gain_nothing(spark):
    rows = X.partition_comparison(spark, SF).where("n = 10").groupBy("partition").agg({"recall": "avg"}).toPandas().set_index("partition")["avg(recall)"]
    assert rows["kmeans"] < rows["sign"] + 0.1


def test_candidates(spark):
    rows = X.text_candidates(spark, SF).toPandas().pivot(index="n", columns="way", values="recall")
    assert (rows.token_hit_dedup >= rows.token_hit_raw).all() and rows.encodings_4096[100] >= rows.token_hit_dedup[100]


def test_merging_flattens(spark):
    rows = X.carve_sweep(spark, SF).where("n = 10").toPandas().set_index("tau")
    assert (rows.groups.sort_index().diff().dropna() >= 0).all()
    assert abs(rows.recall[0.7] - rows.recall[1.1]) <= 0.02


def test_codes(spark):
    rows = X.code_schemes(spark, SF).toPandas()
    assert set(rows[rows.run == 8].ratio) == {32.0, 64.0} and len(rows) == 3 * (1 + len(X.SCHEMES))
    top = rows[rows.n == 100].set_index("scheme").recall
    assert top["pq_256_4"] >= top["pq_16_8"] and top["dense"] - top["pq_256_8"] < 0.1
    assert np.allclose(rows.loss, [rows[(rows.scheme == "dense") & (rows.n == n)].recall.iloc[0] - r for n, r in zip(rows.n, rows.recall, strict=True)])


@pytest.mark.parametrize("name", ["probe_sweep", "progressive_sweep"])
def test_more_work_finds_more(spark, name):
    rows = X.QUERIES[name](spark, SF).toPandas().sort_values("probes" if name == "probe_sweep" else "first_reps")
    assert rows.recall.is_monotonic_increasing and rows.recall.iloc[-1] >= 0.99


def test_corpora(spark):
    for name, make in X.CORPORA.items():
        corpus = make(spark, SF)
        assert corpus.docs.count() > 0 and corpus.queries.count() > 0, name
        assert corpus.docs.columns == ["bag_id", "n", "vecs"], name


def test_near_copies(spark):
    rows = X.near_copies(spark, SF).toPandas()
    assert (rows.query_id // 10_000_000 != rows.doc_id // 10_000_000).all() and rows["rank"].max() <= 5


def test_winners_end_every_tie(spark):
    docs = spark.createDataFrame([(i, 1, b"\x01" * 64) for i in range(250)], "bag_id bigint, n int, vecs binary")
    corpus = X.Corpus(spark.createDataFrame([(1, 1, b"\x01" * 64)], "bag_id bigint, n int, vecs binary"), docs, "sign")
    assert X._winners(corpus).count() == 250


def test_text_grid_has_its_ceiling(spark):
    rows = X.text_grid_recall(spark, SF).toPandas()
    assert len(rows) == 303 and (rows.groupby(["reps", "bits", "proj"]).recall.apply(lambda r: r.sort_values().is_monotonic_increasing)).all()
    ceiling = rows[rows.width == 0].set_index("n").recall
    wide = rows[(rows.width >= 10240)].groupby("n").recall.mean()
    slim = rows[(rows.width > 0) & (rows.width < 500)].groupby("n").recall.mean()
    assert ceiling[100] >= wide[100] - 1e-9 and wide[10] > slim[10]


def test_grid_of_centres_equals_the_encoder(spark):
    corpus = X.vector_bags(spark, SF)
    centers = X._centers(X._word_points(corpus, 512), 2)
    got = X.search.mips_grid(corpus.queries, corpus.docs, 5, X.EncodeParams(64, 6, 64, 20), (3,), (16,), (5,), corpus.kind, centers)
    params = X.EncodeParams(64, 3, 16, 5, partition="center", n_centers=8)
    want = X.search.mips_dense(*X._encoded(corpus, params, centers[8][:5]), 5, params)
    key = ["query_id", "rank", "doc_id"]
    assert sorted(map(tuple, got.select(*key).collect())) == sorted(map(tuple, want.select(*key).collect()))


def test_a_beam_is_the_only_knob(spark, monkeypatch):
    monkeypatch.setattr(X, "BEAMS", (16, 512))
    monkeypatch.setattr(X, "SCHEMES", X.SCHEMES[:1])
    rows = X.graph_code_sweep(spark, SF).toPandas()
    for scheme, part in rows.groupby("scheme"):
        part = part.sort_values("beam").drop_duplicates("beam", keep="last")
        assert (part.n_dist.diff().dropna() >= 0).all() and part.recall10.iloc[-1] >= part.recall10.iloc[0] - 1e-9, scheme
    last = rows[rows.beam == 512].set_index("scheme")
    assert last.recall100["whole"] > 0.95 and last.recall10["pq_256_8"] > 0.6


def test_evaluated_way(spark, monkeypatch):
    monkeypatch.setattr(X, "BEAMS", (128, 512))
    rows = X.evaluated_way(spark, SF).toPandas().sort_values("beam")
    ours = rows[rows.beam > 0]
    assert ours.recall.is_monotonic_increasing and ours.recall.iloc[-1] > 0.9 and set(rows.k) == {100}


def test_own_partitions(spark):
    """A registered partition and one added here encode, fill and search; an unknown one is refused."""
    from setvec.operators import kernels

    corpus = X.vector_bags(spark, SF, sigma=1)
    for name in ("axis", "first_sign"):
        if name == "first_sign":
            kernels.register_partition(name, lambda vecs, params: np.repeat((vecs[:, :1] > 0).astype(np.int64), params.reps, 1))
        params = X.EncodeParams(64, 0, 64, 4, partition=name, n_centers=16 if name == "axis" else 2)
        near = X.search.mips_dense(*X._encoded(corpus, params), 1, params).toPandas()
        assert (near.query_id == near.doc_id).mean() > 0.5, name
    with pytest.raises(ValueError):
        X._encoded(corpus, X.EncodeParams(64, 0, 64, 1, partition="nowhere", n_centers=2))
    with pytest.raises(ValueError):
        kernels.register_partition("sign", lambda v, p: v)
