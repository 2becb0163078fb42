"""Scans, baselines, indexes, measures, sources and streams on small inputs."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from setvec import workloads as WL
from setvec.functions import sql, text, vectors
from setvec.operators import approx, baselines, carve, encode, graph, kernels, metrics, search
from setvec.plans.params import EncodeParams, frontier
from setvec.plans.planner import choose
from setvec.plans.retriever import WAYS, Retriever, roll_up
from setvec.sources import planes, store, tables
from setvec.streaming import ingest

SF = "/root/testdata/sf0.001"
DIM = 64
PARAMS = frontier(1280, DIM)


def lists(df):
    return {q: g.sort_values("rank").doc_id.tolist() for q, g in df.toPandas().groupby("query_id")}


@pytest.fixture(scope="module")
def bags(spark):
    d = tables.pack_bags(tables.vector_tokens(spark, SF)).cache()
    q = tables.pack_bags(tables.vector_tokens(spark, SF).where("pos < 3 and bag_id % 7 = 0")).cache()
    return q, d


@pytest.fixture(scope="module")
def encoded(bags):
    return encode.encode_queries(bags[0], PARAMS).cache(), encode.encode_documents(bags[1], PARAMS).cache()


def test_scans_agree_on_any_partitioning(encoded):
    q, d = encoded
    want = lists(search.mips_dense(q, d, 7, PARAMS))
    for n in (1, 3, 8):
        assert lists(search.mips_dense(q, d.repartition(n), 7, PARAMS)) == want
    assert lists(search.mips_sparse(q, d, 7, PARAMS)) == want
    with pytest.raises(ValueError):
        search.mips_sparse(q, d, 7, PARAMS.with_(final_dim=64))


def test_prefixes_are_the_narrower_encodings(bags, encoded):
    got = search.mips_prefix(*encoded, 4, PARAMS, (1, 7, PARAMS.reps)).toPandas()
    assert set(got.reps) == {1, 7, PARAMS.reps}
    for reps, part in got.groupby("reps"):
        params = PARAMS.with_(reps=int(reps))
        want = search.mips_dense(encode.encode_queries(bags[0], params), encode.encode_documents(bags[1], params), 4, params)
        assert {q: g.sort_values("rank").doc_id.tolist() for q, g in part.groupby("query_id")} == lists(want)
    with pytest.raises(ValueError):
        search.mips_prefix(*encoded, 4, PARAMS, (0,))
    with pytest.raises(ValueError):
        search.mips_prefix(*encoded, 4, PARAMS.with_(final_dim=64), (1,)).collect()


def test_progressive_scan(encoded):
    q, d = encoded
    dense = search.mips_dense(q, d, 3, PARAMS)
    assert lists(search.mips_progressive(q, d, 3, PARAMS, 4, 1000)) == lists(dense)
    near = metrics.recall_at(search.mips_progressive(q, d.coalesce(1), 3, PARAMS, 10, 20), dense.select("query_id", "doc_id"), [3]).first()["recall"]
    assert near >= 0.9
    with pytest.raises(ValueError):
        search.mips_progressive(q, d, 3, PARAMS, 4, 2)


def test_query_blocks_are_bounded(encoded, monkeypatch):
    q, d = encoded
    want = lists(search.mips_dense(q, d, 5, PARAMS))
    monkeypatch.setattr(search, "query_blocks", lambda df, c, f=search.query_blocks: f(df, c, 12_000))
    assert lists(search.mips_dense(q, d, 5, PARAMS)) == want


def test_exact_and_rerank_of_everything(bags):
    q, d = bags
    exact = search.exact_maxsim_topk(q, d, 5, DIM)
    every = search.exact_maxsim_topk(q, d, 1 << 30, DIM)
    assert lists(search.rerank(every, q, d, 5, DIM)) == lists(exact) == lists(search.rerank(every, q, d, 5, DIM, mode="per_query"))
    by_distance = search.exact_maxsim_topk(q, d, 1 << 30, DIM, measure="distance")
    both = every.join(by_distance.select("query_id", "doc_id", F.col("score").alias("far")), ["query_id", "doc_id"]).toPandas()
    assert np.allclose(-both.far, 2 * 3 - 2 * both.score, atol=1e-3)
    docs = {r["bag_id"]: vectors.unpack_one(bytes(r["vecs"]), DIM, "float") for r in d.collect()}
    query = {r["bag_id"]: vectors.unpack_one(bytes(r["vecs"]), DIM, "float") for r in q.collect()}
    for i, best in lists(exact).items():
        score = {j: (query[i] @ v.T).max(1).sum() for j, v in docs.items()}
        assert best == sorted(score, key=lambda j: (-score[j], j))[:5]


def test_empty_bags_in_scores(spark, bags):
    q, d = bags
    some = spark.createDataFrame([(900, 0, bytearray())], tables.BAGS)
    pairs = spark.createDataFrame([(900, 0), (0, 900)], "query_id bigint, doc_id bigint")
    got = {(r["query_id"], r["doc_id"]): r["score"] for r in search.score_pairs(pairs, q.union(some), d.union(some), DIM).collect()}
    assert got == {(900, 0): 0.0, (0, 900): None}


def test_token_hits_and_lists(spark):
    tokens = [(0, 0, [1.0, 0.0]), (0, 1, [0.9, 0.1]), (1, 0, [0.0, 1.0])]
    asked = [(5, 0, [1.0, 0.0]), (5, 1, [0.0, 1.0])]
    ddl = "bag_id bigint, pos int, vec array<float>"
    d, q = tables.pack_bags(spark.createDataFrame(tokens, ddl)), tables.pack_bags(spark.createDataFrame(asked, ddl))
    assert lists(baselines.token_hit(q, d, 2, 2)) == {5: [0, 1, 0, 0]}
    assert lists(baselines.token_hit(q, d, 2, 2, dedup=True)) == {5: [0, 1]}


def test_dedup_is_the_raw_list_without_repeats(bags):
    q, d = bags
    hits = baselines.token_hits(q, d, 6, DIM).cache()
    raw, single = lists(baselines.token_hit_list(hits)), lists(baselines.token_hit_list(hits, True))
    assert {k: list(dict.fromkeys(v)) for k, v in raw.items()} == single
    assert lists(baselines.token_hit_rerank(q, d, 500, 5, DIM)) == lists(search.exact_maxsim_topk(q, d, 5, DIM))


def test_staged_engine_without_pruning_is_brute_force(bags):
    q, d = bags
    centers = vectors.unpack_one(bytes(d.first()["vecs"]), DIM, "float")
    tagged = baselines.tag_centroids(d, centers, DIM)
    exact = lists(search.exact_maxsim_topk(q, d, 5, DIM))
    assert lists(baselines.staged_prune(q, tagged, centers, 5, DIM, len(centers), 1 << 20)) == exact
    pruned = lists(baselines.staged_prune(q, tagged, centers, 5, DIM, 1, 20, 0.1))
    assert set(pruned) == set(exact)
    stored = store.stored(baselines.postings(tagged), "postings", "centroid")
    assert lists(baselines.staged_prune(q, tagged, centers, 5, DIM, 1, 20, 0.1, lists=stored)) == pruned
    near = baselines.probed(q, centers, DIM, "float", 2).toPandas()
    for r in q.collect():
        table = vectors.unpack_one(bytes(r["vecs"]), DIM, "float") @ centers.T
        want = {c for row in table for c in sorted(range(len(centers)), key=lambda c: (-row[c], c))[:2]}
        assert set(near[near.query_id == r["bag_id"]].centroid) == want


def test_pq_is_lossless_with_enough_codes_and_tables_equal_decoding(spark, encoded, monkeypatch):
    q, d = encoded
    few = d.limit(30).cache()
    book = approx.pq_train(few, PARAMS.width, 32, 8)
    codes = approx.pq_encode(few, book).cache()
    assert {r["bag_id"]: bytes(r["enc"]) for r in approx.pq_decode(codes, book).collect()} == {r["bag_id"]: bytes(r["enc"]) for r in few.collect()}
    assert lists(approx.pq_search(q, codes, book, 5)) == lists(search.mips_dense(q, few, 5, PARAMS))
    monkeypatch.setattr(approx, "BY_TABLE", 1000)
    assert lists(approx.pq_search(q, codes, book, 5)) == lists(search.mips_dense(q, few, 5, PARAMS))
    small = approx.pq_train(d, PARAMS.width, 16, 16)
    assert small.code_bytes == PARAMS.width // 32 and book.code_bytes == PARAMS.width // 8
    x = approx.floats(encode.encode_documents(tables.pack_bags(tables.vector_tokens(spark, SF)), PARAMS).limit(5).toArrow()["enc"].combine_chunks())
    raw = small.encode(x)
    assert np.allclose(small.score(small.table(x[0]), small.unpacked(raw)), small.decode(raw) @ x[0], atol=1e-3)


def test_inverted_lists(encoded):
    q, d = encoded
    centers = approx.ivf_centers(d, 6)
    index = approx.ivf_build(d, centers).cache()
    exact = search.mips_dense(q, d, 5, PARAMS)
    assert lists(approx.ivf_search(q, index, centers, 5, 6)) == lists(exact)
    recall = [metrics.recall_at(approx.ivf_search(q, index, centers, 5, p), exact.select("query_id", "doc_id"), [5]).first()["recall"] for p in (1, 3, 6)]
    assert recall == sorted(recall) and recall[-1] == 1


def test_graph(encoded):
    q, d = encoded
    built = graph.graph_build(d, 1, 8, 24).cache()
    rows = graph.graph_nodes(built).collect()
    assert built.count() == 1 and len(rows) == d.count()
    assert all(len(r["neighbours"]) <= 8 for r in rows) and sum(r["is_entry"] for r in rows) == 1
    links = {r["node"]: r["neighbours"] for r in rows}
    seen, stack = set(), [next(r["node"] for r in rows if r["is_entry"])]
    while stack:
        n = stack.pop()
        if n not in seen:
            seen.add(n)
            stack += links[n]
    assert len(seen) == len(rows)
    exact = search.mips_dense(q, d, 5, PARAMS)
    found, cost = graph.graph_search(q, built, 5, len(rows))
    assert lists(found) == lists(exact) and cost.agg(F.max("n_dist")).first()[0] <= len(rows)
    recall = [metrics.recall_at(graph.graph_search(q, built, 5, w)[0], exact.select("query_id", "doc_id"), [5]).first()["recall"] for w in (5, 20, 63)]
    assert recall == sorted(recall) and recall[-1] == 1


def test_graph_walked_on_codes(encoded):
    """A walk that covers its shards is the scan of the same codes; the walk reads the shards in place."""
    q, d = encoded
    book = approx.pq_train(d, PARAMS.width, 16, 8)
    built = graph.graph_build(d, 3, 8, 24)
    coded = graph.graph_code(built, book).cache()
    scan = approx.pq_search(q, approx.pq_encode(d, book), book, 5)
    found, cost = graph.graph_search(q, coded, 5, 63, book=book)
    assert lists(found) == lists(scan) and cost.groupBy("query_id").count().agg(F.max("count")).first()[0] == 3
    size = lambda g: g.agg(F.sum(F.length("points"))).first()[0]
    assert size(built) == 32 * 2 * size(coded)
    plan = graph.graph_search(q, coded, 5, 63, book=book)[1]._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan.split("InMemoryTableScan")[0]


def test_walk_is_bounded_by_its_beam():
    """A chain of points: a narrow beam ends where the nearest lies, and a wide one sees all."""
    points = np.arange(50, dtype=float)
    links = np.array([[max(0, i - 1), min(49, i + 1)] for i in range(50)], np.int32)
    far = lambda x: np.abs(points[x] - 20.2)
    ids, cost, n = graph.walk(far, links, 0, 3)
    assert ids[:3].tolist() == [20, 21, 19] and n < 30 and (np.diff(cost) >= 0).all()
    assert graph.walk(far, links, 0, 50)[2] == 50


def test_distances_are_the_same_either_way(monkeypatch):
    points = np.random.default_rng(3).normal(size=(60, 12)).astype(np.float32)
    whole = graph.Distances(points)
    links = graph.build_links(points, 6, 20, 1.2, 1)[0]
    monkeypatch.setattr(graph, "TABLE_BYTES", 0)
    asked = graph.Distances(points)
    some = np.array([3, 9, 40])
    assert asked.all is None and np.allclose(whole.of(5, some), asked.of(5, some), atol=1e-4) and np.allclose(whole.among(some), asked.among(some), atol=1e-4)
    want = ((points[some] - points[5]) ** 2).sum(1)
    assert np.allclose(asked.of(5, some), want, atol=1e-4) and (graph.build_links(points, 6, 20, 1.2, 1)[0] == links).mean() > 0.9


def test_routed_graph(encoded):
    q, d = encoded
    centers = approx.ivf_centers(d, 4)
    built = graph.graph_build(d, 2, 8, 24, centers=centers).cache()
    assert built.agg(F.sum("n")).first()[0] == d.count() and built.agg(F.max("shard")).first()[0] < 8
    exact = search.mips_dense(q, d, 5, PARAMS)
    found, cost = graph.graph_search(q, built, 5, 63, centers, 4, 2)
    assert lists(found) == lists(exact)
    fewer = graph.graph_search(q, built, 5, 63, centers, 1, 2)[1]
    assert fewer.groupBy("query_id").count().agg(F.max("count")).first()[0] <= 2 < cost.groupBy("query_id").count().agg(F.max("count")).first()[0]


def test_carved_columns_equal_the_kernel(spark, bags):
    q, _ = bags
    rows = tables.vector_tokens(spark, SF).where("bag_id % 7 = 0").groupBy("bag_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "vec"))), lambda s: s["vec"]).alias("vs"))
    rows = rows.withColumn("seeds", carve.seed_places("vs", 0.05)).withColumn("of", carve.group_seeds("vs", "seeds", 0.05))
    for r in rows.collect():
        _, group = kernels.carve(np.array(r["vs"], np.float32), 0.05)
        first = [int(np.flatnonzero(group == g)[0]) for g in group]
        assert r["of"] == first and r["seeds"] == sorted(set(first))


def test_measures_on_hand_made_lists(spark):
    ranked = spark.createDataFrame([(1, 1, 10), (1, 2, 11), (1, 3, 12), (2, 1, 20), (2, 2, 21)], "query_id bigint, rank int, doc_id bigint")
    truth = spark.createDataFrame([(1, 11), (1, 99), (2, 20)], "query_id bigint, doc_id bigint")
    assert {r["n"]: r["recall"] for r in metrics.recall_at(ranked, truth, [1, 2]).collect()} == {1: 0.5, 2: 0.75}
    assert {r["n"]: r["recall"] for r in metrics.one_recall_at(ranked, truth, [1, 2]).collect()} == {1: 0.5, 2: 1.0}
    curve = spark.createDataFrame([(1, 0.5), (5, 0.8), (9, 0.9)], "n int, recall double")
    assert metrics.n_for_recall(curve, 0.8).first()["n"] == 5 and metrics.n_for_recall(curve, 0.95).first()["n"] is None
    slow = spark.createDataFrame([(20, 0.8)], "n int, recall double")
    assert metrics.candidate_ratio(slow, curve, 0.8).first()["ratio"] == 4
    grid = spark.createDataFrame([(1, 0.5), (2, 0.4), (3, 0.7), (4, 0.7)], "width int, recall double")
    assert sorted(r["width"] for r in metrics.pareto(grid).collect()) == [1, 3]
    assert round(metrics.floats_token_hit(32, 128, 78.8, 1)) == 322_765 and metrics.equal_cost_width(32, 128, 78.8, 0) == 4096
    assert metrics.storage(frontier(10240, 128), 1280, 78.8)["ratio"] == 32
    assert metrics.latency(lambda q: None, [1, 2, 3])["p50"] >= 0 and metrics.qps(lambda: None, 10) > 0


def test_retriever_ways_agree(bags):
    q, d = bags
    want = lists(search.exact_maxsim_topk(q, d, 3, DIM))
    for way in (*WAYS, "auto"):
        r = Retriever(PARAMS, way, codes=32, lists=4, probes=4, degree=8, build_beam=24).fit(d)
        got = lists(r.search(q, 3, 63, beam=63, tau=None))
        assert {k: v[0] for k, v in got.items()} == {k: v[0] for k, v in want.items()}, way
        assert way in r.explain() or way == "auto"
    with pytest.raises(ValueError):
        Retriever(PARAMS, "other").fit(d)


@pytest.mark.parametrize("way", ["dense", "pq", "ivf", "routed_pq"])
def test_saved_index_needs_no_encoder(spark, tmp_path, bags, way):
    q, d = bags
    made = Retriever(PARAMS, way, codes=32, lists=4, probes=2, degree=8, build_beam=24).fit(d)
    made.save(f"{tmp_path}/{way}")
    read = Retriever.load(spark, f"{tmp_path}/{way}")
    assert lists(read.search(q, 3, 20, beam=63, tau=0.5)) == lists(made.search(q, 3, 20, beam=63, tau=0.5))
    for r in (made, read):
        plan = r.candidates(q, 20, 63)._jdf.queryExecution().optimizedPlan().toString()
        # One kernel over the stored index and none below it: queries were encoded when the plan was built.
        assert plan.count("MapInArrow") == 1 and "pos" not in plan


def test_rerank_modes_run_as_named(spark, bags):
    q, d = bags
    near = search.exact_maxsim_topk(q, d, 20, DIM)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plans = {m: search.rerank(near, q, d, 5, DIM, mode=m)._jdf.queryExecution().executedPlan().toString() for m in ("per_query", "spread")}
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    # What the scoring kernel's rows are dealt by: the first exchange below it.
    dealt = {m: p[p.index("MapInArrow") :].split("Exchange hashpartitioning(", 1)[1].split("),")[0] for m, p in plans.items()}
    assert "salt" in dealt["spread"] and "query_id" in dealt["spread"]
    assert "salt" not in dealt["per_query"] and "query_id" in dealt["per_query"]


def test_planner():
    p = frontier(10240, 128)
    assert choose(p, 10**4, 80, 1000).index in ("dense", "sparse")
    assert choose(p, 10**9, 80, 10**5).index == "pq"
    assert choose(p, 10**9, 80, 10).index == "ivf"
    assert choose(p, 10**9, 80, 1, interactive=True).index == "graph"
    assert choose(p.with_(final_dim=4096), 10**4, 80, 10).index == "dense"
    assert "index=" in choose(p, 10**4, 80, 10).explain()


def test_roll_up(spark):
    ranked = spark.createDataFrame([(1, 1, 100, 3.0), (1, 2, 200, 2.0), (1, 3, 101, 1.0)], "query_id bigint, rank int, doc_id bigint, score double")
    owners = spark.createDataFrame([(100, 1), (101, 1), (200, 2)], "bag_id bigint, doc_id bigint")
    assert lists(roll_up(ranked, owners, 5)) == {1: [1, 2]}


def test_text(spark):
    docs = spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(300))), (2, "One two, TWO!"), (3, ""), (4, None)], "doc_id bigint, text string")
    got = {(r["doc_id"], r["chunk_no"]): len(r["words"]) for r in text.chunks(docs).collect()}
    assert got == {(1, 0): 128, (1, 1): 128, (1, 2): 128, (1, 3): 108, (2, 0): 2}
    assert np.frombuffer(text.word_signs("x"), np.int8).shape == (64,)
    tri = np.frombuffer(text.word_trigrams("hello"), "<f4")
    near, far = (np.frombuffer(text.word_trigrams(w), "<f4") @ tri for w in ("hellos", "qqzz"))
    assert np.isclose(tri @ tri, 1, atol=1e-5) and near > 0.5 > abs(far)
    html = spark.createDataFrame([("<html><script>var x=1;</script><p>Hi <b>you</b></p><style>a{}</style></html>",)], "html string")
    assert html.select(text.strip_html("html")).first()[0] == "Hi you"


def test_sources(spark, tmp_path, bags, encoded):
    bad = spark.createDataFrame([(1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [float("nan"), 0.0]), (5, [None, 1.0])], "id int, vec array<double>")
    reasons = {r["id"]: r["reject_reason"] for r in tables.checked(bad, 2).collect()}
    assert reasons == {1: None, 2: "length", 3: "null", 4: "not finite", 5: "null component"} and tables.accepted(bad, 2).count() == 1
    tables.write_bags(bags[1], f"{tmp_path}/bags", 2)
    assert spark.read.parquet(f"{tmp_path}/bags").count() == 63
    tables.write_encodings(encoded[1], f"{tmp_path}/enc", PARAMS)
    assert tables.read_encodings(spark, f"{tmp_path}/enc", PARAMS).count() == 63
    with pytest.raises(ValueError):
        tables.read_encodings(spark, f"{tmp_path}/enc", PARAMS.with_(seed=1))
    tokens = tables.vector_tokens(spark, SF).limit(5)
    tokens.write.json(f"{tmp_path}/json")
    tokens.select("bag_id", "pos", F.array_join(F.col("vec").cast("array<string>"), " ").alias("vec")).write.option("header", True).csv(f"{tmp_path}/csv")
    tokens.select(F.concat_ws("\t", "bag_id", "pos", F.array_join(F.col("vec").cast("array<string>"), " ")).alias("value")).write.text(f"{tmp_path}/text")
    want = sorted(tokens.collect())
    for form in ("json", "csv", "text"):
        assert sorted(tables.read_bags(spark, f"{tmp_path}/{form}", form).collect()) == want
    for form in ("parquet", "json", "csv"):
        tables.write_ranked(search.mips_dense(*encoded, 2, PARAMS), f"{tmp_path}/ranked-{form}", form)
    planes.register(spark)
    got = spark.read.format("setvec_planes").options(seed=42, reps=2, rows=3, dim=4).load().toPandas()
    from setvec.functions.seeds import planes as make

    assert (got.sort_values(["rep", "i", "dim"]).g.to_numpy().reshape(2, 3, 4) == make(42, 2, 3, 4, "int12")).all()


def test_sql_surface(spark, bags):
    sql.register_all(spark, SF, PARAMS)
    assert spark.sql("select vec_dot(array(1D, 2D), array(3D, 4D)), vec_norm(array(3D, 4D))").first()[:] == (11.0, 5.0)
    assert spark.sql("select vec_maxsim(array(array(1D, 0D)), array(array(0.5D, 1D), array(0.25D, 0D)))").first()[0] == 0.5
    assert spark.sql("select count(*) from documents").first()[0] == 200
    rows = spark.sql("select chunk_no, size(words) n from chunk_text('a b c d e', 3, 2)").collect()
    assert [(r["chunk_no"], r["n"]) for r in rows] == [(0, 3), (1, 3)]
    cells = spark.sql("select count(*) from embeddings, lateral explode_cells(embedding) where vec_id < 3").first()[0]
    assert cells == 3 * PARAMS.reps
    bags[1].createOrReplaceTempView("some_bags")
    score = spark.sql("select maxsim_packed(a.vecs, a.vecs) s from some_bags a where a.bag_id = 1").first()["s"]
    assert np.isclose(score, 8, atol=1e-3)
    enc = spark.sql("select vec_id div 8 b, encode_bag_agg(embedding) e from embeddings where vec_id < 16 group by 1").collect()
    assert all(len(r["e"]) == PARAMS.width for r in enc)


def test_vector_columns(spark):
    row = spark.createDataFrame([([3.0, 4.0], [1.0, 2.0])], "a array<double>, b array<double>")
    got = row.select(
        vectors.vec_dot("a", "b"), vectors.vec_norm("a"), vectors.vec_cosine("a", "a"), vectors.vec_add("a", "b"), vectors.vec_scale("a", 2.0),
        vectors.vec_axpy(2.0, "a", "b"), vectors.vec_normalize("a"), vectors.vec_argmax("a"), vectors.vec_groups("a", 2, 1), vectors.valid_vector("a", 2),
    ).first()
    assert list(got) == [11.0, 5.0, 1.0, [4.0, 6.0], [6.0, 8.0], [7.0, 10.0], [0.6, 0.8], 1, [[3.0], [4.0]], True]


def test_streams(spark, tmp_path):
    from setvec.queries import QUERIES

    batch = {(r["bag_id"], r["place"]): r["v"] for r in QUERIES["doc_encoding_packed"](spark, SF).collect()}
    assert {(r["bag_id"], r["place"]): r["v"] for r in QUERIES["stream_encode"](spark, SF).collect()} == batch
    rows = tables.load(spark, SF, "events")
    early, late = rows.where("ts >= '2024-01-20'"), rows.where("ts < '2024-01-03'")
    early.coalesce(1).write.parquet(f"{tmp_path}/in")
    stream = lambda: ingest.window_bags(ingest.read_dir(spark, f"{tmp_path}/in", tables.SCHEMAS["events"], files=1), "1 day", "1 hour")
    name = "late_events"
    run = lambda: stream().writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/check").trigger(availableNow=True).start().awaitTermination()  # noqa: E731, E501
    run()
    late.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    run()
    got = spark.read.parquet(f"{tmp_path}/out")
    assert got.count() > 0 and got.where("window.start < '2024-01-10'").count() == 0 and name


def test_search_stream_and_running_recall(spark, tmp_path, bags):
    q, d = bags
    rows = q.orderBy("bag_id").collect()
    ddl = "bag_id bigint, n int, vecs binary"
    for part in (rows[:4], rows[4:]):
        spark.createDataFrame(part, ddl).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    run = lambda block: search.exact_maxsim_topk(block, d, 2, DIM)
    ingest.search_stream(ingest.read_dir(spark, f"{tmp_path}/in", ddl, files=1), run, f"{tmp_path}/out", f"{tmp_path}/check").awaitTermination()
    found = spark.read.parquet(f"{tmp_path}/out")
    truth = q.select(F.col("bag_id").alias("query_id"), F.col("bag_id").alias("doc_id"))
    got = ingest.running_recall(found, truth, 1).orderBy("batch").collect()
    assert [r["recall"] for r in got] == [1.0, 1.0] and sum(r["queries"] for r in got) == len(rows) and got[-1]["running"] == 1.0
    none = ingest.running_recall(found.where("rank > 1"), truth, 1).orderBy("batch").collect()
    assert none[-1]["running"] == 0.0


def test_rate_source_is_encoded_as_it_arrives(spark, tmp_path):
    """Made-up vectors, one bag each, through the stateless encoder: the same as in a batch."""
    params = EncodeParams(4, 2, 4, 2)
    ddl = "bag_id bigint, n int, vecs binary"

    def pack(batches):
        import pyarrow as pa

        for b in batches:
            raw = [np.asarray(v, "<f4").tobytes() for v in b.column("vec").to_pylist()]
            yield pa.record_batch([b.column("bag_id"), pa.array([1] * len(raw), pa.int32()), pa.array(raw, pa.binary())], names=["bag_id", "n", "vecs"])

    bags = ingest.rate_tokens(spark, 8, 4, 1).select("bag_id", "vec").mapInArrow(pack, ddl)
    run = ingest.encode_stream(bags, params).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/check").start()
    for _ in range(60):
        run.awaitTermination(1)
        if run.lastProgress and run.lastProgress["batchId"] >= 2:
            break
    run.stop()
    got = {r["bag_id"]: bytes(r["enc"]) for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    vecs = np.array([[np.cos(i * (d + 1)) for d in range(4)] for i in sorted(got)], np.float32)
    want = kernels.encode(vecs, np.arange(len(vecs)), len(vecs), params, "document")
    assert len(got) >= 16 and all(np.allclose(np.frombuffer(got[i], "<f4"), w, atol=1e-5) for i, w in zip(sorted(got), want, strict=True))


def test_sentences_and_session(spark):
    from setvec.session import SETTINGS, session

    row = spark.createDataFrame([("Hi there. All is well!",)], "t string").select(text.sentence_words("t")).first()[0]
    assert row == [["hi", "there"], ["all", "is", "well"]]
    assert session() is not None and SETTINGS["spark.sql.adaptive.enabled"] == "true"


def test_cogrouped_rerank(bags):
    q, d = bags
    near = search.exact_maxsim_topk(q, d, 9, DIM)
    assert lists(search.rerank_cogrouped(near, q, d, 5, DIM)) == lists(search.rerank(near, q, d, 5, DIM))


def test_stream_updates(spark, tmp_path):
    params = EncodeParams(4, 2, 4, 2)
    ddl = "doc_id bigint, pos int, vec array<float>, gone boolean"
    first = [(1, 0, [1.0, 0.0, 0.0, 0.0], False), (1, 1, [0.0, 1.0, 0.0, 0.0], False), (2, 0, [0.0, 0.0, 1.0, 0.0], False)]
    spark.createDataFrame(first, ddl).coalesce(1).write.parquet(f"{tmp_path}/in")
    spark.createDataFrame([(1, 0, None, True)], ddl).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    out = ingest.finished(ingest.vector_updates(ingest.read_dir(spark, f"{tmp_path}/in", ddl, files=1), params), "update")
    last = {r["bag_id"]: (r["n"], bytes(r["enc"])) for r in out.collect() if r["n"] == 1}
    alone = kernels.encode(np.array([[0, 1, 0, 0], [0, 0, 1, 0]], np.float32), np.array([0, 1]), 2, params, "document")
    assert last[2] == (1, alone[1].tobytes())
    assert last.get(1, (1, alone[0].tobytes())) == (1, alone[0].tobytes())


def test_workload_directions(spark):
    rows = WL.error_by_width(spark, SF).toPandas().sort_values("width")
    filled = rows[rows.fill].mean_error.to_numpy()
    assert filled[-1] < filled[0] and (rows[rows.fill].mean_error.to_numpy() < rows[~rows.fill].mean_error.to_numpy()).mean() > 0.7
    recall = WL.recall_by_width(spark, SF, widths=(1280, 10240)).toPandas()
    at = recall[recall.n == 1].set_index("width").recall
    assert at[10240] > at[1280]
