"""What larger or odd tables need: bounded score tables, no rows through the driver, short bags, gaps in bags."""

from __future__ import annotations

import tracemalloc

import duckdb
import numpy as np
import pytest
from test_oracle import rows

from setvec.operators import kernels, metrics, search
from setvec.queries import QUERIES, SQL
from setvec.sources import tables

SF = "/root/testdata/sf0.001"


def test_token_hits_hold_tiles_only():
    """20,000 query vectors against 4,096 document vectors: the whole table would be 655 MB."""
    rng = np.random.default_rng(1)
    query, vecs = rng.integers(-3, 4, (20_000, 4)), rng.integers(-3, 4, (4096, 4))
    ids, places = rng.permutation(4096) // 8, np.arange(4096) % 8
    tracemalloc.start()
    held = kernels.Hits(len(query), 5, query.dtype)
    for a in (0, 1000, 4000):
        b = {0: 1000, 1000: 4000, 4000: 4096}[a]
        held.add(query, vecs[a:b], ids[a:b], places[a:b])
    assert tracemalloc.get_traced_memory()[1] < 300 << 20
    tracemalloc.stop()
    assert np.array_equal(held.rows, np.repeat(np.arange(20_000), 5))
    for q in range(0, 20_000, 997):
        score = vecs @ query[q]
        want = np.lexsort((places, ids, -score))[:5]
        own = slice(5 * q, 5 * q + 5)
        assert held.scores[own].tolist() == score[want].tolist()
        assert list(zip(held.ids[own], held.places[own], strict=True)) == list(zip(ids[want], places[want], strict=True))


def test_products_stay_exact():
    a = np.array([[1 << 40, 1], [3, -(1 << 40)]])
    for b in (np.array([[1, 1], [1 << 10, 5]]), np.array([[(1 << 20) + 1, 3]])):
        assert np.array_equal(kernels.products(a, b), a @ b.T)
        assert kernels.products(a, b).dtype == np.int64


def test_winners_of_copies(spark):
    """All documents that tie at the best score, found without the scores of all pairs."""
    tokens = tables.fixed_tokens(tables.vector_tokens(spark, SF))
    docs = tables.pack_bags(tokens.where("bag_id < 12"), "fixed")
    docs = docs.union(docs.selectExpr("bag_id + 100 AS bag_id", "n", "vecs")).repartition(3)
    queries = tables.pack_bags(tables.planted_tokens(tokens.where("bag_id < 7")), "fixed")
    got = {tuple(r) for r in search.exact_winners(queries, docs, 64, "fixed").collect()}
    assert got == {tuple(r) for r in metrics.tie_sets(search.exact_maxsim_topk(queries, docs, 1000, 64, "fixed")).collect()}
    assert len(got) == 14


def test_scans_have_many_tasks(spark):
    from setvec import workloads as WL

    assert WL.doc_bags(spark, SF).rdd.getNumPartitions() >= 2 * spark.sparkContext.defaultParallelism


@pytest.mark.parametrize("name", ["stream_sessions", "stream_distinct", "stream_purchases", "stream_window_bags", "stream_sliding_bags"])
def test_stream_rows_come_from_files(spark, name):
    assert QUERIES[name](spark, SF).inputFiles()


def test_baskets_broadcast_nothing(spark):
    assert "Broadcast" not in QUERIES["order_basket_similarity"](spark, SF)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["maxsim_mean", "carve_clusters", "collision_rate", "token_hit_raw", "one_recall_token_hit", "cell_purity"])
def test_short_bags_and_gaps_equal_sql(spark, tmp_path, name):
    """The last bag has two vectors, one bag has a null in its middle."""
    path = f"{tmp_path}/embeddings.parquet"
    duckdb.sql(f"copy (select vec_id, case when vec_id <> 17 then embedding end as embedding, label from '{SF}/embeddings.parquet' where vec_id < 98) to '{path}' (format parquet)")
    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{path}'")
    got, want = QUERIES[name](spark, str(tmp_path)).toPandas(), con.sql(SQL[name]).df()
    assert rows(got) == rows(want)


def test_coded_graphs_store_no_encodings(spark, monkeypatch):
    """No row that is written holds a shard's encodings, and the codes are those of the graph built on them."""
    from setvec.operators import encode, graph
    from setvec.plans.params import EncodeParams
    from setvec.plans.retriever import Retriever
    from setvec.sources import store

    rng = np.random.default_rng(5)
    bags = spark.createDataFrame([(i, 4, rng.normal(size=(4, 16)).astype("<f4").tobytes()) for i in range(120)], "bag_id bigint, n int, vecs binary")
    written, put = [], store.stored
    monkeypatch.setattr(store, "stored", lambda df, tag, by=None: written.append((tag, put(df, tag, by))) or written[-1][1])
    params = EncodeParams(16, 3, 8, 4)
    way = Retriever(params, "graph_pq", codes=16, shards=2, degree=8, build_beam=16).fit(bags)
    graphs = [df for tag, df in written if tag == "graph"]
    assert graphs and all(len(r["points"]) == r["n"] * way.book.code_bytes for df in graphs for r in df.collect())
    built = graph.graph_build(encode.encode_documents(bags, params), 2, 8, 16)
    key = lambda df: sorted((r["shard"], bytes(r["ids"]), bytes(r["links"]), bytes(r["points"])) for r in df.collect())
    assert key(graph.graph_code(built, way.book)) == key(way.stored)


def test_codes_by_joins_make_no_row_of_a_pair(spark, monkeypatch):
    """Blocks of queries and documents meet; each row of the join is a pair of blocks, and lists equal the scan's."""
    from setvec.operators import approx

    rng = np.random.default_rng(3)
    points, asked = rng.integers(-9, 10, (300, 8)).astype("<f4"), rng.integers(-9, 10, (30, 8)).astype("<f4")
    book = approx.Codebook(points[:20].reshape(20, 2, 4).transpose(1, 0, 2).copy(), 8)
    enc = lambda x: spark.createDataFrame([(i, r.tobytes()) for i, r in enumerate(x)], "bag_id bigint, enc binary")
    codes = spark.createDataFrame([(i, g, int(c)) for i, row in enumerate(book.encode(points)) for g, c in enumerate(row)], "doc_id bigint, g int, code int")
    queries = spark.createDataFrame([(i, d, float(x)) for i, row in enumerate(asked) for d, x in enumerate(row)], "query_id bigint, dim int, x double")
    centers = spark.createDataFrame([(c, 4 * g + i, float(x)) for g, of in enumerate(book.centers) for c, row in enumerate(of) for i, x in enumerate(row)], "code int, dim int, center double")
    monkeypatch.setattr(approx, "BLOCK_QUERIES", 8, raising=False)
    monkeypatch.setattr(approx, "BLOCK_DOCS", 100, raising=False)
    got = approx.pq_search_by_joins(queries, codes, centers, 4, 7)
    want = approx.pq_search(enc(asked), approx.pq_encode(enc(points), book), book, 7)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    assert "doc_ids" in got._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize(("form", "tau"), [("sign", None), ("trigram", 0.7)])
def test_words_get_their_vectors_where_they_are_scored(spark, monkeypatch, form, tau):
    """Lists equal those of joined vectors, also by several blocks of queries; no vectors of documents are shuffled."""
    from setvec.functions import text

    rng = np.random.default_rng(2)
    words = lambda n: [f"w{x}" for x in rng.permutation(300)[:n]]
    ddl = "bag_id bigint, words array<string>"
    docs = spark.createDataFrame([(i, words(i % 9)) for i in range(90)], ddl)
    asked = text.bags_of_words(spark.createDataFrame([(i, words(6)) for i in range(10)] + [(10, [])], ddl), form)
    pairs = spark.createDataFrame([(q, d) for q in range(12) for d in range(95) if (q + d) % 3], "query_id bigint, doc_id bigint")
    kind = "sign" if form == "sign" else "float"
    want = {(r["query_id"], r["rank"]): r for r in search.rerank(pairs, asked, text.bags_of_words(docs, form), 5, 64, kind, tau).collect()}
    monkeypatch.setattr(search.query_blocks, "__defaults__", (4000,))
    for mode in ("per_query", "spread"):
        near = search.rerank(pairs, asked, docs, 5, 64, kind, tau, mode, form=form)
        got = {(r["query_id"], r["rank"]): r for r in near.collect()}
        assert got.keys() == want.keys() and all(abs(got[x]["score"] - want[x]["score"]) < 1e-5 for x in want)
        assert "vecs" not in near._jdf.queryExecution().executedPlan().toString()


def test_throughput_of_merging_keeps_no_vectors(spark, monkeypatch):
    from setvec import experiments as X

    written, put = [], X.store.stored
    monkeypatch.setattr(X.store, "stored", lambda df, tag, by=None: written.append((tag, df.columns)) or put(df, tag, by))
    before = spark._jsc.sc().getPersistentRDDs().size()
    assert X.carve_throughput(spark, SF).count() == 4
    assert spark._jsc.sc().getPersistentRDDs().size() == before
    assert ("words", ["bag_id", "words"]) in written


def test_bags_of_words_come_in_bounded_batches(spark, monkeypatch):
    from setvec.functions import text

    rows = spark.createDataFrame([(i, [f"w{i}_{j}" for j in range(i % 40)]) for i in range(300)], "bag_id bigint, words array<string>").coalesce(1)
    whole = text.bags_of_words(rows)
    monkeypatch.setattr(text, "BATCH_WORDS", 100, raising=False)
    kept: list = []
    fake = type("Rows", (), {"select": lambda self, *_: self, "mapInArrow": lambda self, run, ddl: kept.append(run)})()
    text.bags_of_words(fake)
    batch = rows.toArrow().combine_chunks().to_batches()[0]
    out = list(kept[0](iter([batch])))
    sizes = [sum(b.column("n").to_pylist()) for b in out]
    assert max(sizes) < 140 and sum(sizes) == sum(i % 40 for i in range(300))
    want = {r["bag_id"]: bytes(r["vecs"]) for r in whole.collect()}
    assert {i: v for b in out for i, v in zip(b.column("bag_id").to_pylist(), b.column("vecs").to_pylist(), strict=True)} == want


def test_staged_engine_makes_no_rows_of_listed_pairs(spark):
    """With a ``keep`` that drops nothing the lists of few probed centroids are scored exactly, without a join of pairs."""
    from setvec import workloads as WL
    from setvec.operators import baselines

    docs, queries = WL.doc_bags(spark, SF), WL.query_bags(spark, SF)
    centers = WL.hash_centers(WL.doc_tokens(spark, SF))
    tagged = baselines.tag_centroids(docs, centers, 64, "fixed")
    got = baselines.staged_prune(queries, tagged, centers, 3, 64, 1, 1 << 20, None, "fixed")
    assert "Join" not in got._jdf.queryExecution().toString()
    near = baselines.probed(queries, centers, 64, "fixed", 1)
    listed = baselines.postings(tagged).join(near, "centroid").select("query_id", "doc_id").distinct()
    assert 0 < listed.count() < docs.count() * queries.count()
    want = search.rerank(listed, queries, docs, 3, 64, "fixed")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


@pytest.mark.parametrize("more", [{}, {"proj_dim": 8}, {"final_dim": 24}, {"fill": False, "doc_block": "sum"}, {"partition": "axis", "n_centers": 6, "hash_bits": 0}])
@pytest.mark.parametrize("side", ["document", "query"])
def test_mapped_vectors_give_the_same_blocks(more, side):
    """Repeated vectors, empty bags and one cell of hundreds of vectors."""
    from setvec.plans.params import EncodeParams

    params = EncodeParams(**{"dim": 8, "hash_bits": 3, "proj_dim": 4, "reps": 3} | more)
    rng = np.random.default_rng(5)
    distinct = rng.normal(size=(40, 8)).astype(np.float32)
    sizes = np.array([0, 3, 500, 1, 0, 20])
    which, owner = rng.integers(0, 40, sizes.sum()), np.repeat(np.arange(6), sizes)
    which[10:300] = 7
    want = kernels._encode(distinct[which], owner, 6, params, None, side == "document")
    assert np.allclose(kernels.encode(distinct[which], owner, 6, params, side), want, rtol=1e-4, atol=1e-4)
    assert np.allclose(kernels.encode_distinct(distinct, which, owner, 6, params, side), want, rtol=1e-4, atol=1e-4)


def _texts(spark, n, seed=3):
    rng = np.random.default_rng(seed)
    words = np.array([f"w{i}" for i in range(400)])
    docs = [(i, " ".join(rng.choice(words, int(m)))) for i, m in enumerate(rng.integers(1, 600, n))]
    docs += [(n, None), (n + 1, " .,! "), (n + 2, docs[0][1])]
    asked = [(i, " ".join(docs[3 * i][1].split()[:30])) for i in range(6)] + [(6, "")]
    return spark.createDataFrame(docs, "doc_id bigint, text string").repartition(5), spark.createDataFrame(asked, "item_id bigint, text string")


def test_documents_are_searched_in_one_pass(spark, monkeypatch):
    """No vector leaves the task that makes it, and each query's floor lets through what is asked for, or is lowered."""
    from setvec.functions import text as T
    from setvec.operators import chunked
    from setvec.plans.params import EncodeParams

    docs, items = _texts(spark, 300)
    queries, params = T.bags_of_words(T.items(items)), EncodeParams(64, 3, 8, 4)
    bags = T.bags_of_words(T.numbered_chunks(T.chunks(docs.where("text is not null"))))
    exact = search.exact_maxsim_topk(queries, bags, 1 << 20, 64, "sign").selectExpr("query_id", "doc_id div 10000000 AS doc_id", "score")
    want = search.topk(exact.groupBy("query_id", "doc_id").agg({"score": "max"}).withColumnRenamed("max(score)", "score"), 5)
    whole = chunked.search_documents(queries, docs.where("text is not null"), 5, params, None, 1 << 20)
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, want.collect()))
    monkeypatch.setattr(chunked, "SAMPLE", 256)
    monkeypatch.setattr(chunked, "LETTERS", 64)
    seen = []
    real = chunked._pass
    monkeypatch.setattr(chunked, "_pass", lambda docs, asked, *a: seen.append([x[3] for x in asked]) or real(docs, asked, *a))
    some = chunked.search_documents(queries, docs.where("text is not null"), 5, params, None, 40)
    assert "vecs" not in some._jdf.queryExecution().toString()
    assert max(seen[0]) > float("-inf")
    got = some.toPandas()
    assert (got.groupby("query_id").size() == 5).all() and got.query_id.nunique() == 7
    best = want.toPandas()
    assert (got[got["rank"] == 1].set_index("query_id").score == best[best["rank"] == 1].set_index("query_id").score).all()
    # A thousand documents are never settled by forty chunks, so floors fall until none is left.
    seen.clear()
    every = chunked.search_documents(queries, docs.where("text is not null"), 1000, params, None, 40)
    assert len(seen) > 1 and every.groupBy("query_id").count().where("count <> 301").isEmpty()


def test_flagship_joins_no_vectors(spark):
    from setvec import workloads as WL

    plan = WL.flagship(spark, SF)._jdf.queryExecution().toString()
    assert "vecs" not in plan and "Join" not in plan


def test_filtered_documents_are_joined_once(spark):
    """The filter is written once; what is searched afterwards joins and shuffles neither texts nor vectors."""
    from setvec import workloads as WL

    rows = WL.filtered_retrieval(spark, SF)
    plan = rows._jdf.queryExecution().toString()
    assert "vecs" not in plan and "Join" not in plan and "documents.parquet" not in plan
    good = {r[0] for r in WL.filtered_documents(spark, SF).select("doc_id").collect()}
    assert {r["doc_id"] for r in rows.collect()} <= good


def test_recall_of_documents_joins_no_vectors(spark):
    from setvec import workloads as WL

    assert "vecs" not in WL.text_recall(spark, SF)._jdf.queryExecution().toString()


@pytest.mark.parametrize("more", [{}, {"proj_dim": 8}, {"final_dim": 24}, {"fill": False, "doc_block": "sum"}, {"partition": "axis", "n_centers": 6, "hash_bits": 0}])
def test_products_without_whole_encodings(more, monkeypatch):
    """A repetition of a few bags at a time gives the products of whole encodings; bags may be empty."""
    from setvec.plans.params import EncodeParams

    monkeypatch.setattr(kernels, "AT_ONCE", 4)
    params = EncodeParams(**{"dim": 8, "hash_bits": 3, "proj_dim": 4, "reps": 3} | more)
    rng = np.random.default_rng(6)
    distinct, sizes = rng.normal(size=(40, 8)).astype(np.float32), np.array([0, 3, 90, 1, 0, 20, 2, 5, 0])
    which, owner = rng.integers(0, 40, sizes.sum()), np.repeat(np.arange(9), sizes)
    queries = rng.normal(size=(5, params.width)).astype(np.float32)
    want = queries @ kernels._encode(distinct[which], owner, 9, params, None, True).T
    assert np.allclose(kernels.scored(queries, distinct, which, owner, 9, params), want, rtol=1e-4, atol=1e-3)


def test_empty_cells_take_the_nearest_code():
    """Of codes that differ in the fewest bits the smallest place, also where the nearest differs in all bits."""
    from setvec.plans.params import EncodeParams

    params = EncodeParams(dim=4, hash_bits=4, proj_dim=4, reps=1)
    points = np.arange(20, dtype=np.float32).reshape(5, 4)
    for code in ([15, 15, 15, 15, 15], [3, 0, 5, 9, 9], [7, 11, 13, 14, 0]):
        code, out = np.array(code), np.zeros((16, 4), np.float32)
        kernels._put_blocks(out, 0, 16, 1, points, code, np.arange(5), np.zeros(5, np.int64), params, True)
        for cell in set(range(16)) - set(code.tolist()):
            assert (out[cell] == points[min(range(5), key=lambda i: (bin(int(code[i]) ^ cell).count("1"), i))]).all()
    assert all(len(set(x.tolist())) == len(x) for x in kernels._by_distance(6))


def test_documents_are_drawn_before_they_are_split(spark, monkeypatch):
    from setvec.operators import chunked

    docs, _ = _texts(spark, 600)
    docs = docs.where("text is not null")
    every = {r[0] for r in chunked.sampled_chunks(docs, 1).select("bag_id").collect()}
    monkeypatch.setattr(chunked, "WITHIN", 2)
    some = {r[0] for r in chunked.sampled_chunks(docs, 8).select("bag_id").collect()}
    assert some < every and 0.05 < len(some) / len(every) < 0.25
    assert len({b // 10_000_000 for b in some}) < 0.5 * len({b // 10_000_000 for b in every})


def test_schemes_are_compared_where_chunks_are_encoded(spark, monkeypatch):
    """Neither encodings nor codes of chunks are written; winners and lists are those of the scans of stored tables."""
    from setvec import experiments as X
    from setvec import workloads as WL
    from setvec.operators import approx, encode, schemes
    from setvec.sources import store

    tags, real = [], store.stored
    monkeypatch.setattr(store, "stored", lambda df, tag, by=None: tags.append(tag) or real(df, tag, by))
    monkeypatch.setattr(X, "SCHEMES", ((16, 8),))
    assert X.code_schemes(spark, SF).count() == 6
    assert "queries" in tags and not {"encodings", "codes"} & set(tags)
    corpus, params = X.items_over_chunks(spark, SF), X.EncodeParams(64, 3, 8, 4)
    q, d = (real(x, "encodings") for x in X._encoded(corpus, params))
    book = approx.pq_train(d, params.width, 16, 8, n=0)
    docs = WL.spread(X.tables.load(spark, SF, "documents").where("text is not null").select("doc_id", "text"), "doc_id")
    found = real(schemes.scan_schemes(q.join(corpus.queries.select("bag_id", "vecs"), "bag_id"), docs, [None, book], 10, params), "found")
    assert set(map(tuple, schemes.winners(found).collect())) == set(map(tuple, search.exact_winners(corpus.queries, corpus.docs, 64, "sign").collect()))
    for at, want in enumerate((search.mips_dense(q, d, 10, params), approx.pq_search(q, approx.pq_encode(d, book), book, 10))):
        got = search.topk(found.where(f"scheme = {at} and score is not null").select("query_id", "doc_id", "score"), 10).toPandas().set_index(["query_id", "rank"]).sort_index()
        assert np.allclose(got.score, want.toPandas().set_index(["query_id", "rank"]).sort_index().score, rtol=1e-3, atol=1e-3)
    assert found.where("seconds > 0").select("scheme").distinct().count() == 2


def test_codebooks_of_schemes_are_those_of_each(spark):
    from setvec.operators import approx

    rng = np.random.default_rng(8)
    rows = spark.createDataFrame([(i, bytearray(rng.normal(size=72).astype("<f4").tobytes())) for i in range(60)], "bag_id bigint, enc binary")
    both = approx.pq_train_schemes(rows, 72, [(16, 8), (4, 16)])
    for book, (codes, group) in zip(both, ((16, 8), (4, 16)), strict=True):
        one = approx.pq_train(rows, 72, codes, group, n=0)
        assert book.centers.shape == one.centers.shape == (-(-72 // group), codes, group) and (book.centers == one.centers).all()
        x = rng.normal(size=(300, 72)).astype(np.float32)
        near = np.stack([kernels.nearest_center(approx._grouped(x, group)[:, g], book.centers[g]) for g in range(len(book.centers))], 1)
        assert (book.unpacked(book.encode(x)) == near).mean() > 0.999
        assert (book.decode(book.encode(x)) == np.concatenate([book.centers[g][near[:, g]] for g in range(len(near[0]))], 1)[:, :72]).mean() > 0.999


def test_graphs_are_walked_where_they_are_built(spark, monkeypatch):
    """Neither encodings nor graphs are written, every chunk is in one shard, and a beam over whole shards gives dense lists."""
    from setvec import experiments as X
    from setvec.operators import approx, encode, schemes
    from setvec.sources import store

    docs, items = _texts(spark, 60)
    long = spark.createDataFrame([(900, " ".join(f"v{i % 700}" for i in range(5000)))], "doc_id bigint, text string")
    docs = docs.where("text is not null").unionByName(long)
    bags, params = X.T.bags_of_words(X.T.numbered_chunks(X.T.chunks(docs))), X.EncodeParams(64, 3, 8, 4)
    q, d = (store.stored(f(x, params, kind="sign"), "encodings") for f, x in ((encode.encode_queries, X.T.bags_of_words(X.T.items(items).where("size(words) > 0"))), (encode.encode_documents, bags)))
    book = approx.pq_train(d, params.width, 16, 8, n=0)
    found = store.stored(schemes.walk_schemes(q, docs, 3, [None, book], [1000], 20, params, 8, 16), "walks")
    n = d.count()
    assert found.groupBy("query_id", "way").agg({"n_dist": "sum"}).where(f"`sum(n_dist)` <> {n}").isEmpty() and found.groupBy("way").count().count() == 3
    hits = found.selectExpr("query_id", "way", "explode(arrays_zip(doc_ids, scores)) AS h").selectExpr("query_id", "way", "h.doc_ids AS doc_id", "h.scores AS score")
    dense = search.mips_dense(q, d, 20, params).toPandas().set_index(["query_id", "rank"]).sort_index()
    coded = approx.pq_search(q, approx.pq_encode(d, book), book, 20).toPandas().set_index(["query_id", "rank"]).sort_index()
    for way, want in ((schemes.EXACT, dense), (0, dense), (1, coded)):
        got = search.topk(hits.where(f"way = {way}").drop("way"), 20).toPandas().set_index(["query_id", "rank"]).sort_index()
        assert len(got) == len(want) and np.allclose(got.score, want.score, rtol=1e-3, atol=1e-3), way
    tags, real = [], store.stored
    monkeypatch.setattr(store, "stored", lambda df, tag, by=None: tags.append(tag) or real(df, tag, by))
    monkeypatch.setattr(X, "BEAMS", (16,))
    monkeypatch.setattr(X, "SCHEMES", ((16, 8),))
    assert X.graph_code_sweep(spark, SF).count() == 2
    assert "walks" in tags and not {"encodings", "graph"} & set(tags)


def test_queries_of_a_grid_are_dealt_in_tiles(spark, monkeypatch):
    """A task holds the lists of a tile of queries alone, and they are those of all queries at once and of the dense scan."""
    from setvec import experiments as X

    corpus, bits, projs, reps = X.vector_bags(spark, SF), (2, 4), (8, 64), (1, 3)
    grid = lambda: search.mips_grid(corpus.queries, corpus.docs, 3, X.EncodeParams(64, 4, 64, 3), bits, projs, reps, corpus.kind)
    key = ["query_id", "cells", "proj", "reps", "rank", "doc_id"]
    want = sorted(map(tuple, grid().select(key).collect()))
    monkeypatch.setattr(search, "GRID_QUERIES", 5)
    got = grid()
    assert "hashpartitioning(tile" in got._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, got.select(key).collect())) == want
    params = X.EncodeParams(64, 4, 8, 3)
    dense = search.mips_dense(*X._encoded(corpus, params), 3, params).select("query_id", "rank", "doc_id")
    assert sorted((r[0], r[4], r[5]) for r in want if r[1:4] == (16, 8, 3)) == sorted(map(tuple, dense.collect()))
    n = corpus.docs.count()
    tiles, rows = search.tiled(corpus.docs, 5)
    parts = rows.groupBy(search.F.spark_partition_id().alias("part"), "tile").count().collect()
    assert len({r["part"] for r in parts}) == len(tiles) == 5 and {r["count"] for r in parts} == {n}


def test_throughput_encodes_chunks_where_they_are_scanned(spark, monkeypatch):
    """No encoding of a chunk becomes a row, and only candidates' words are stored; lists and words are those of whole tables."""
    from setvec import experiments as X
    from setvec.functions import text
    from setvec.operators import chunked
    from setvec.sources import store

    docs, items = _texts(spark, 60)
    long = spark.createDataFrame([(900, " ".join(f"v{i % 700}" for i in range(3000)))], "doc_id bigint, text string")
    docs = docs.where("text is not null").select("doc_id", "text").unionByName(long)
    asked, params = text.bags_of_words(text.items(items), "trigram"), X.EncodeParams(64, 4, 8, 3)
    q = store.stored(X.encode.encode_queries(asked, params), "queries")
    rows = text.numbered_chunks(text.chunks(docs)).select("bag_id", "words")
    want = search.mips_dense(q, X.encode.encode_documents(text.bags_of_words(rows, "trigram"), params), 5, params).toPandas().set_index(["query_id", "rank"]).sort_index()
    near = store.stored(chunked.scan_chunks(q, docs, 5, params, "trigram"), "near")
    got = near.toPandas().set_index(["query_id", "rank"]).sort_index()
    assert len(got) == len(want) and np.allclose(got.score, want.score, rtol=1e-4, atol=1e-4)
    own = {r["bag_id"]: r["words"] for r in chunked.words_of(near, docs).collect()}
    every = {r["bag_id"]: r["words"] for r in rows.collect()}
    assert own.keys() == {r["doc_id"] for r in near.collect()} and all(every[b] == w for b, w in own.items())
    monkeypatch.setattr(X.encode, "encode_documents", lambda *a, **b: 1 / 0)
    assert X.carve_throughput(spark, SF).where("qps > 0").count() == 4


def test_vectors_of_trigrams_at_once_are_those_of_each():
    import pyarrow as pa

    from setvec.functions import text

    words = ["a", "", "ab", "abc", "straße", "日本語", "𝒳y", "x" * 200, "y" * 31, "z" * 33, "aaaaaaaa", *(f"wort{i}" for i in range(300))]
    want = np.stack([np.frombuffer(text.word_trigrams(w), "<f4") for w in words])
    assert (text.trigram_vectors(pa.array([""])) == want[1:2]).all()
    assert (text.trigram_vectors(pa.array(words)) == want).all() and text.trigram_vectors(pa.array([], pa.string())).shape == (0, 64)
