"""Sweeps and comparisons over several corpora, each as (spark, sf_dir) -> DataFrame.

A corpus is a pair of packed bag tables, queries and documents. What a query is differs between corpora, the settings
do not. Times are wall times of whole jobs and differ between runs; everything else repeats.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce, wraps

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setvec import workloads as WL
from setvec.functions import text as T
from setvec.functions import seeds, vectors
from setvec.operators import approx, baselines, carve, chunked, encode, graph, kernels, metrics, schemes, search
from setvec.plans.params import EncodeParams, frontier
from setvec.plans.retriever import Retriever
from setvec.sources import store, tables

DIM = 64
CUTS = [1, 10, 100]
WIDTHS = (1280, 2560, 5120, 10240)


def _all(rows: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def _timed(df: DataFrame) -> tuple[DataFrame, float]:
    """The result, written, and the seconds that took."""
    t = time.perf_counter()
    df = store.stored(df, "timed")
    return df, time.perf_counter() - t


_KEPT: dict[tuple, DataFrame] = {}


def _once(run: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    """A long sweep runs once a session and folder; its rows are written, and read again by what is made from them."""

    @wraps(run)
    def kept(spark: SparkSession, sf_dir: str) -> DataFrame:
        key = (run.__name__, spark.sparkContext.applicationId, store.CLEARED[0], sf_dir)
        if key not in _KEPT:
            _KEPT[key] = store.stored(run(spark, sf_dir), run.__name__)
        return _KEPT[key]

    return kept


# --- corpora ------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Corpus:
    queries: DataFrame
    docs: DataFrame
    kind: str

    def kept(self) -> Corpus:
        return Corpus(self.queries.persist(), self.docs.persist(), self.kind)


def items_over_chunks(spark: SparkSession, sf_dir: str, where: str = "true", form: str = "sign") -> Corpus:
    docs = tables.load(spark, sf_dir, "documents").where(where)
    bags = T.bags_of_words(WL.spread(T.numbered_chunks(T.chunks(docs))), form)
    queries = T.bags_of_words(T.items(tables.load(spark, sf_dir, "benchmark")), form)
    return Corpus(queries, bags, "sign" if form == "sign" else "float")


def turns(spark: SparkSession, sf_dir: str) -> Corpus:
    """User turns over assistant turns."""
    rows = tables.load(spark, sf_dir, "conversations").where("text is not null")
    rows = rows.select((F.col("conv_id") * 1000 + F.col("turn")).alias("bag_id"), "role", T.words("text").alias("words")).where(F.size("words") > 0)
    own = rows.where("role = 'user'")
    said = rows.where("role = 'assistant'").withColumn("words", F.array_distinct("words"))
    return Corpus(T.bags_of_words(own), T.bags_of_words(WL.spread(said)), "sign")


def page_chunks(spark: SparkSession, sf_dir: str) -> Corpus:
    """Items over chunks of web pages."""
    pages = tables.load(spark, sf_dir, "pages").select("page_id", T.strip_html("html").alias("text"))
    bags = T.bags_of_words(WL.spread(T.numbered_chunks(T.chunks(pages, key="page_id"))))
    return Corpus(T.bags_of_words(T.items(tables.load(spark, sf_dir, "benchmark"))), bags, "sign")


def vector_bags(spark: SparkSession, sf_dir: str, size: int = 8, sigma: int = 2) -> Corpus:
    """Planted queries, four vectors at most, over bags of ``size`` vectors."""
    tokens = tables.fixed_tokens(tables.vector_tokens(spark, sf_dir, size))
    return Corpus(tables.pack_bags(tables.planted_tokens(tokens, sigma), "fixed"), tables.pack_bags(tokens, "fixed"), "fixed")


def baskets(spark: SparkSession, sf_dir: str) -> Corpus:
    """Orders as bags of their parts' brand, type and size; queries are the first lines of every hundredth order."""
    lines = tables.load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    parts = tables.load(spark, sf_dir, "part").select("p_partkey", F.array("p_brand", "p_type", F.concat(F.lit("size "), F.col("p_size"))).alias("w"))
    rows = lines.join(parts, lines["l_partkey"] == parts["p_partkey"]).select(F.col("l_orderkey").alias("bag_id"), F.col("l_linenumber").alias("line"), "w")
    packed = lambda r: r.groupBy("bag_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("line", "w"))), lambda x: x["w"])).alias("words"))
    docs = packed(rows).withColumn("words", F.array_distinct("words"))
    return Corpus(T.bags_of_words(packed(rows.where("bag_id % 100 = 0 and line <= 2"))), T.bags_of_words(docs), "sign")


CORPORA: dict[str, Callable[[SparkSession, str], Corpus]] = {
    "chunks_en": lambda s, d: items_over_chunks(s, d, "lang = 'en'"),
    "chunks_other": lambda s, d: items_over_chunks(s, d, "lang is null or lang <> 'en'"),
    "turns": turns,
    "pages": page_chunks,
    "vectors": vector_bags,
    "baskets": baskets,
}


def _encoded(corpus: Corpus, params: EncodeParams, centers: np.ndarray | None = None) -> tuple[DataFrame, DataFrame]:
    return encode.encode_queries(corpus.queries, params, centers, corpus.kind), encode.encode_documents(corpus.docs, params, centers, corpus.kind)


def _winners(corpus: Corpus) -> DataFrame:
    """All documents with a query's best exact score."""
    return search.exact_winners(corpus.queries, corpus.docs, DIM, corpus.kind).persist()


# --- width, partition, final map, seeds -----------------------------------------------------------------------------


GRID_BITS, GRID_PROJ, GRID_REPS = (2, 3, 4, 5, 6), (8, 16, 32, 64), (1, 5, 10, 15, 20)


def _share(near: DataFrame, truth: DataFrame, key: list[str], cuts: list[int], owners: bool = False) -> DataFrame:
    """key, n, recall: the mean share of a query's documents that are among its first ``n`` chunks."""
    if owners:
        near = near.withColumn("doc_id", F.expr("doc_id div 10000000"))
    # What is not wanted goes before the sums, as lists are many times longer.
    first = near.join(F.broadcast(truth), ["query_id", "doc_id"], "left_semi").groupBy("query_id", "doc_id", *key).agg(F.min("rank").alias("rank"))
    wanted = truth.groupBy("query_id").agg(F.count("*").alias("wanted"))
    per = first.join(F.broadcast(wanted), "query_id").groupBy(*key).agg(*[F.sum(F.when(F.col("rank") <= n, 1 / F.col("wanted")).otherwise(0.0)).alias(f"r{n}") for n in cuts])
    curve = F.explode(F.array(*[F.struct(F.lit(n).alias("n"), F.col(f"r{n}").alias("hit")) for n in cuts])).alias("x")
    return per.select(*key, curve).join(F.broadcast(wanted.agg(F.count("*").alias("queries"))), F.lit(True)).select(*key, "x.n", (F.col("x.hit") / F.col("queries")).alias("recall"))


def _grid(spark: SparkSession, corpus: Corpus, truth: DataFrame, k: int, cuts: list[int], owners: bool, centers: dict[int, np.ndarray] | None = None) -> DataFrame:
    """cells, proj, reps, width, n, recall for all hundred settings. The lists are kept, as the measure reads them again."""
    near = search.mips_grid(corpus.queries, corpus.docs, k, EncodeParams(DIM, 6, DIM, 20), GRID_BITS, GRID_PROJ, GRID_REPS, corpus.kind, centers)
    key = ["cells", "proj", "reps"]
    near = store.stored(near.select("query_id", *key, "rank", "doc_id"), "grid")
    every = spark.createDataFrame([(1 << b, p, r) for b in GRID_BITS for p in GRID_PROJ for r in GRID_REPS], "cells int, proj int, reps int")
    got = every.crossJoin(spark.createDataFrame([(n,) for n in cuts], "n int")).join(_share(near, truth, key, cuts, owners), [*key, "n"], "left")
    return got.select(*key, (F.col("cells") * F.col("proj") * F.col("reps")).alias("width"), "n", F.coalesce("recall", F.lit(0.0)).alias("recall"))


def _first_winners(corpus: Corpus) -> DataFrame:
    """One exact winner for each query, that of the smallest id."""
    return _winners(corpus).groupBy("query_id").agg(F.min("doc_id").alias("doc_id")).persist()


@_once
def grid_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """1Recall of planted queries for all hundred settings of repetitions, bits and projected numbers: reps, bits, proj,
    width, n, recall. Planted queries have no ties."""
    corpus = vector_bags(spark, sf_dir).kept()
    rows = _grid(spark, corpus, _first_winners(corpus), 10, WL.CUTS, False)
    return rows.select("reps", F.log2("cells").cast("int").alias("bits"), "proj", "width", "n", "recall")


def grid_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The settings of the grid that no setting of at most their width reaches at n = 1."""
    return metrics.pareto(grid_recall(spark, sf_dir).where("n = 1"))


@_once
def text_grid_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled recall of items over chunks for the whole grid, and of exact scoring (width 0), the ceiling: reps, bits,
    proj, width, n, recall."""
    corpus = items_over_chunks(spark, sf_dir).kept()
    truth = WL.containment_truth(spark, sf_dir).persist()
    rows = _grid(spark, corpus, truth, 100, CUTS, True).select("reps", F.log2("cells").cast("int").alias("bits"), "proj", "width", "n", "recall")
    exact = search.exact_maxsim_topk(corpus.queries, corpus.docs, 100, DIM, corpus.kind).withColumn("all", F.lit(0))
    top = _share(exact, truth, ["all"], CUTS, True).select(*[F.lit(0).alias(c) for c in ("reps", "bits", "proj", "width")], "n", "recall")
    return rows.unionByName(top)


def text_grid_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Settings on the frontier of labelled recall at n = 10."""
    return metrics.pareto(text_grid_recall(spark, sf_dir).where("n = 10 and width > 0"))


def _word_points(corpus: Corpus, most: int) -> np.ndarray:
    """Distinct vectors of a hash sample of at most 256 bags, at most ``most`` of them in an order drawn from the seed."""
    rows = approx.hash_sample(corpus.docs, 256, purpose="center").orderBy("bag_id").limit(256).collect()
    points = np.unique(np.concatenate([vectors.unpack_one(bytes(r["vecs"]), DIM, corpus.kind) for r in rows]).astype(np.float32), axis=0)
    return points[seeds.generator("center", 42).permutation(len(points))[:most]]


def _centers(points: np.ndarray, rounds: int) -> dict[int, np.ndarray]:
    """Centres of 20 repetitions by number of cells, trained for ``rounds`` (0: drawn only)."""
    out = {}
    for b in GRID_BITS:
        drawn = [points[seeds.generator("center", 42, r).permutation(len(points))[: 1 << b]] for r in range(max(GRID_REPS))]
        drawn = [np.concatenate([x, np.repeat(x[:1], (1 << b) - len(x), 0)]) for x in drawn]
        out[1 << b] = np.stack([kernels.lloyd(points, x, rounds) if rounds else x for x in drawn]).astype(np.float32)
    return out


def partition_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sign cells against k-means and random centres over the whole grid, planted queries: partition, cells, proj, reps,
    width, n, recall."""
    corpus = vector_bags(spark, sf_dir).kept()
    win = _first_winners(corpus)
    points = _word_points(corpus, 4096)
    # Whole-number vectors are compared as floats of the same scale.
    ways = {"sign": None, "random": _centers(points, 0), "kmeans": _centers(points, 10)}
    return _all([_grid(spark, corpus, win, 10, WL.CUTS, False, c).withColumn("partition", F.lit(name)) for name, c in ways.items()])


def text_partition_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for items over chunks by labelled recall, sign cells against k-means."""
    corpus = items_over_chunks(spark, sf_dir).kept()
    truth = WL.containment_truth(spark, sf_dir).persist()
    ways = {"sign": None, "kmeans": _centers(_word_points(corpus, 4096), 5)}
    return _all([_grid(spark, corpus, truth, 100, CUTS, True, c).withColumn("partition", F.lit(name)) for name, c in ways.items()])


def final_map_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal widths and cells, with the inner projection or with twice the repetitions, no inner projection and a last
    map: width, mapped, n, recall. The noise of both maps grows with the number of cells, so cells are kept equal."""
    corpus = vector_bags(spark, sf_dir).kept()
    win, rows = _winners(corpus), []
    for width in (1280, 2560, 5120):
        for mapped in (False, True):
            params = frontier(width, DIM)
            if mapped:
                params = params.with_(proj_dim=DIM, reps=2 * params.reps, final_dim=width)
            one = metrics.one_recall_at(search.mips_dense(*_encoded(corpus, params), 10, params), win, WL.CUTS)
            rows.append(one.select(F.lit(width).alias("width"), F.lit(mapped).alias("mapped"), "n", "recall"))
    return _all(rows)


def seed_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and deviation of 1Recall over ten seeds at two widths."""
    corpus = vector_bags(spark, sf_dir).kept()
    win, rows = _winners(corpus), []

    def run(width: int) -> Callable[[int], DataFrame]:
        def one(seed: int) -> DataFrame:
            params = frontier(width, DIM, seed=seed)
            return metrics.one_recall_at(search.mips_dense(*_encoded(corpus, params), 10, params), win, WL.CUTS)

        return one

    for width in (2560, 10240):
        rows.append(metrics.recall_variance(run(width), list(range(1, 11))).withColumn("width", F.lit(width)))
    return _all(rows)


def bag_size_effect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """1Recall and error by vectors in a document, at one width: size, n, recall."""
    rows = []
    for size in (2, 4, 8, 16, 32):
        corpus = vector_bags(spark, sf_dir, size).kept()
        params = frontier(2560, DIM)
        one = metrics.one_recall_at(search.mips_dense(*_encoded(corpus, params), 10, params), _winners(corpus), WL.CUTS)
        rows.append(one.withColumn("size", F.lit(size)))
    return _all(rows)


def heldout_one_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The hard case: queries of held-out vectors that have no near neighbour. width, n, recall."""
    own, rest = tables.heldout_tokens(spark, sf_dir)
    corpus = Corpus(tables.pack_bags(own), tables.pack_bags(rest), "float").kept()
    win, rows = _winners(corpus), []
    for width in WIDTHS:
        params = frontier(width, DIM)
        rows.append(metrics.one_recall_at(search.mips_dense(*_encoded(corpus, params), 10, params), win, WL.CUTS).withColumn("width", F.lit(width)))
    return _all(rows)


# --- candidates -----------------------------------------------------------------------------------------------------


def text_one_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Items over chunks by width: width, n, recall."""
    corpus = items_over_chunks(spark, sf_dir).kept()
    win, rows = _winners(corpus), []
    for width in WIDTHS:
        params = frontier(width, DIM)
        rows.append(metrics.one_recall_at(search.mips_dense(*_encoded(corpus, params), 100, params), win, CUTS).withColumn("width", F.lit(width)))
    return _all(rows)


#: The setting that is compared with the per-token baseline before its last map.
MAPPED = EncodeParams(DIM, 6, DIM, 40)
CANDIDATE_CUTS = [1, 5, 10, 20, 40, 60, 80, 100, 150, 200, 300, 600, 1200]


def _candidates(corpus: Corpus, widths: tuple[int, ...]) -> DataFrame:
    """way, n, recall of the exact winners: encodings of 40 repetitions, 64 cells and no inner projection, mapped to each
    width, and the per-token lists with and without repeats."""
    win, most = _winners(corpus), max(CANDIDATE_CUTS)
    ways = {f"encodings_{w}": search.mips_dense(*_encoded(corpus, MAPPED.with_(final_dim=w)), most, MAPPED.with_(final_dim=w)) for w in widths}
    hits = baselines.token_hits(corpus.queries, corpus.docs, 100, DIM, corpus.kind).persist()
    ways["token_hit_raw"], ways["token_hit_dedup"] = baselines.token_hit_list(hits), baselines.token_hit_list(hits, True)
    return _all([metrics.one_recall_at(r, win, CANDIDATE_CUTS).withColumn("way", F.lit(w)) for w, r in ways.items()])


def text_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates for a recall on items over chunks, width 4,096."""
    return _candidates(items_over_chunks(spark, sf_dir).kept(), (4096,))


def text_candidates_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same at width 10,240."""
    return _candidates(items_over_chunks(spark, sf_dir).kept(), (10240,))


def vector_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both widths for planted queries over bags of embeddings."""
    return _candidates(vector_bags(spark, sf_dir).kept(), (4096, 10240))


def text_floats_scanned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numbers that a query's scan reads on chunks, for encodings of width 10,240 and the per-token baseline."""
    size = T.chunks(tables.load(spark, sf_dir, "documents")).agg(F.count("*").alias("n"), F.avg(F.size("words")).alias("m"))
    equal = F.lit(float(T.QUERY_WORDS * DIM)) * F.col("m")
    return size.select("n", (F.col("n") * 10240).alias("encoding"), F.round(equal * F.col("n"), 3).alias("token_hit"), F.round(equal, 3).alias("equal_width"), F.lit(T.QUERY_WORDS * DIM).alias("free_search_width"))


# --- merged queries -------------------------------------------------------------------------------------------------


def carve_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trigram word vectors re-ranked with merged queries: tau, n, recall of the exact n best for n of 10, 100 and 1,000,
    groups, fewer. Twice as many candidates as the longest list are re-scored."""
    corpus = items_over_chunks(spark, sf_dir, form="trigram").kept()
    most = 1000
    truth = search.exact_maxsim_topk(corpus.queries, corpus.docs, most, DIM).persist()
    params = frontier(2560, DIM)
    near = store.stored(search.mips_dense(*_encoded(corpus, params), 2 * most, params), "near")

    def run(tau: float) -> DataFrame:
        found = search.rerank(near, corpus.queries, corpus.docs, most, DIM, corpus.kind, tau).persist()
        stats = metrics.carve_stats(carve.carve_bags(corpus.queries, tau, DIM))
        cuts = [metrics.recall_at(found, truth.where(F.col("rank") <= n).select("query_id", "doc_id"), [n]) for n in (10, 100, most)]
        return _all(cuts).join(stats, F.lit(True))

    return metrics.sweep(run, [0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.1])


def carve_throughput(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries per second of re-ranking a thousand candidates, a query's in one task or spread over tasks, with and without
    merging: mode, tau, qps (best of three runs). Candidates come from one pass over all chunks; a run re-ranks them from
    their stored words."""
    # Several Python workers follow one another in a task, so what each takes at once is kept small.
    store.bounded_bytes(spark, 8 << 20)
    docs = tables.load(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text")
    queries = store.stored(T.bags_of_words(T.items(tables.load(spark, sf_dir, "benchmark")), "trigram"), "queries")
    params = frontier(2560, DIM)
    # Chunks are encoded where they are scanned: as vectors or encodings they are many times larger.
    asked = encode.encode_queries(queries, params, kind="float")
    near = store.stored(chunked.scan_chunks(asked, WL.spread(docs, "doc_id"), 1000, params, "trigram"), "near")
    # Only candidates are re-ranked, so each run reads the words of these and not those of the corpus.
    chunks = store.stored(chunked.words_of(near, docs), "words")
    n, rows = queries.count(), []
    for mode in ("per_query", "spread"):
        for tau in (None, 0.7):
            times = []
            for _ in range(3):
                # Queries are merged where the search is called, so its call counts.
                t = time.perf_counter()
                store.stored(search.rerank(near, queries, chunks, 10, DIM, "float", tau, mode, form="trigram"), "timed")
                times.append(time.perf_counter() - t)
            rows.append((mode, tau, n / min(times)))
    return spark.createDataFrame(rows, "mode string, tau double, qps double")


# --- codes ----------------------------------------------------------------------------------------------------------


SCHEMES = ((256, 8), (256, 4), (256, 16), (16, 4), (16, 8))


def _scheme_books(rows: DataFrame, n: int, schemes: tuple[tuple[int, int], ...], params: EncodeParams) -> list[approx.Codebook]:
    """Codebooks trained on the encodings of about 2,000 chunks (bag_id, words) of ``n``."""
    return approx.pq_train_schemes(encode.encode_documents(T.bags_of_words(approx.hash_sample(rows, 2000, n=n)), params, kind="sign"), params.width, list(schemes))


def code_schemes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the exact winner, its loss against whole encodings, size and speed by code scheme at width 10,240: scheme,
    codes, run, bytes, ratio, qps, n, recall, loss. Every chunk is encoded once, coded by all schemes and searched in the task
    that encoded it, and nothing but hits is written; ``qps`` is of the seconds that searches take there on all cores."""
    docs = tables.load(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text")
    params = frontier(10240, DIM)
    asked = T.bags_of_words(T.items(tables.load(spark, sf_dir, "benchmark")))
    queries = store.stored(encode.encode_queries(asked, params, kind="sign").join(asked.select("bag_id", "vecs"), "bag_id"), "queries")
    rows = T.numbered_chunks(T.chunks(docs))
    books = [None, *_scheme_books(rows, rows.count(), SCHEMES, params)]
    found = store.stored(schemes.scan_schemes(queries, WL.spread(docs, "doc_id"), books, max(CUTS), params), "found")
    win = store.stored(schemes.winners(found), "winners")
    took = {r["scheme"]: r["s"] for r in found.where("seconds is not null").groupBy("scheme").agg(F.sum("seconds").alias("s")).collect()}
    n, cores, out, whole = queries.count(), spark.sparkContext.defaultParallelism, [], None
    for at, (book, (codes, run)) in enumerate(zip(books, ((0, 0), *SCHEMES), strict=True)):
        name, size = ("dense", 4 * params.width) if book is None else (f"pq_{codes}_{run}", book.code_bytes)
        hits = found.where((F.col("scheme") == at) & F.col("score").isNotNull()).select("query_id", "doc_id", "score")
        curve = store.stored(metrics.one_recall_at(search.topk(hits, max(CUTS)), win, CUTS), "curve")
        whole = whole or curve
        head = {"scheme": name, "codes": codes, "run": run, "bytes": size, "ratio": 4 * params.width / size, "qps": float(n * cores / took[at]) if took.get(at) else None}
        out.append(curve.join(metrics.delta(whole, curve), "n").select(*[F.lit(x).alias(c) for c, x in head.items()], "n", "recall", "loss"))
    return _all(out)


#: Graphs of the sweeps: degree and build beam, and the beams of a search.
GRAPH, BEAMS = (32, 64), (16, 32, 64, 128, 256, 512)


def graph_code_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The evaluated search by its one knob: graphs built on whole encodings of width 10,240, walked on codes of each
    scheme and on the encodings themselves. scheme, beam, recall10, recall100 (of the dense scan's lists), distances a
    query, qps. A shard's words are encoded, linked and walked in one task, and only what walks find is written; ``qps`` is
    of the seconds that walks take there on all cores. Beams below 100 walk as 100 does, once."""
    docs = tables.load(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text")
    params, k = frontier(10240, DIM), 100
    queries = store.stored(encode.encode_queries(T.bags_of_words(T.items(tables.load(spark, sf_dir, "benchmark"))), params, kind="sign"), "queries")
    rows = T.numbered_chunks(T.chunks(docs))
    n, size, cores = queries.count(), rows.count(), spark.sparkContext.defaultParallelism
    shards = max(cores, graph.shard_count(size, params.width))
    ways = [("whole", None), *((f"pq_{codes}_{run}", book) for (codes, run), book in zip(SCHEMES[:3], _scheme_books(rows, size, SCHEMES[:3], params), strict=True))]
    beams = sorted({max(k, beam) for beam in BEAMS})
    found = store.stored(schemes.walk_schemes(queries, docs, shards, [b for _, b in ways], beams, k, params, *GRAPH), "walks")
    hits = found.select("way", "beam", "query_id", F.explode(F.arrays_zip("doc_ids", "scores")).alias("h"))
    lists = store.stored(search.topk(hits.select("query_id", "way", "beam", F.col("h.doc_ids").alias("doc_id"), F.col("h.scores").alias("score")), k, "way", "beam"), "lists")
    exact = lists.where(F.col("way") == schemes.EXACT).select("query_id", "doc_id", "rank")
    costs = {(r["way"], r["beam"]): (r["d"], r["s"]) for r in found.groupBy("way", "beam").agg(F.sum("n_dist").alias("d"), F.sum("seconds").alias("s")).collect()}
    out = []
    for at, (name, _) in enumerate(ways):
        for beam in (max(k, b) for b in BEAMS):
            kept, (dist, took) = lists.where((F.col("way") == at) & (F.col("beam") == beam)), costs.get((at, beam), (0, 0))
            recall = [metrics.recall_at(kept, exact.where(F.col("rank") <= c).select("query_id", "doc_id"), [c]).select(F.col("recall").alias(f"recall{c}")) for c in (10, k)]
            head = {"n_dist": dist / n if n else None, "qps": n * cores / took if took else None}
            one = recall[0].join(recall[1], F.lit(True))
            out.append(one.select(F.lit(name).alias("scheme"), F.lit(beam).alias("beam"), "recall10", "recall100", *[F.lit(x).cast("double").alias(c) for c, x in head.items()]))
    return _all(out)


# --- end to end -----------------------------------------------------------------------------------------------------


COMPARED = 2560


def _ours(corpus: Corpus, index: str = "pq") -> Callable[[int, int], DataFrame]:
    """A search at one setting for every corpus: width ``COMPARED`` (published: 10,240, which takes minutes a corpus here), codes of 256 centres for 8 numbers, close query vectors merged
    from 0.7 on. The index is built and stored before; what is called is the search alone."""
    way = Retriever(frontier(COMPARED, DIM), index, corpus.kind, sample=512, degree=GRAPH[0], build_beam=GRAPH[1]).fit(corpus.docs)
    tau = round(0.7 * (1 << 40)) if corpus.kind == "fixed" else 0.7
    return lambda k, candidates: way.search(corpus.queries, k, candidates, None, tau)


def _staged(corpus: Corpus, n_centers: int = 256) -> Callable[[int, int], DataFrame]:
    """The staged engine with its index stored before: tags, and lists partitioned by centroid. Centroids come from all
    vectors of a hash sample of at most 1,024 bags."""
    rows = approx.hash_sample(corpus.docs, 1024).orderBy(F.xxhash64("bag_id"), "bag_id").limit(1024).collect()
    points = np.unique(np.concatenate([vectors.unpack_one(bytes(r["vecs"]), DIM, corpus.kind) for r in rows]).astype(np.float32), axis=0)
    start = points[np.random.default_rng(42).permutation(len(points))[:n_centers]]
    centers = kernels.lloyd(points, start, 5)
    if corpus.kind == "fixed":
        centers = np.rint(centers).astype(np.int64)
    tagged = store.stored(baselines.tag_centroids(corpus.docs, centers, DIM, corpus.kind), "tagged")
    # One file for each centroid, not one from every task.
    lists = store.stored(baselines.postings(tagged).repartition("centroid"), "postings", "centroid")
    return lambda k, candidates: baselines.staged_prune(corpus.queries, tagged, centers, k, DIM, 16, 4 * candidates, None, corpus.kind, lists)


@_once
def compared_over_corpora(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Our whole way and the staged engine with one setting on every corpus, both over stored indexes: corpus, way, k,
    recall of the exact k best for k of 100 and 1,000 (all, where a corpus has fewer), milliseconds a query."""
    rows, cuts = [], (100, 1000)
    for name, make in CORPORA.items():
        corpus = make(spark, sf_dir)
        corpus = Corpus(store.stored(corpus.queries, "queries"), store.stored(corpus.docs, "bags"), corpus.kind)
        n = corpus.queries.count()
        if not n:
            continue
        truth = store.stored(search.exact_maxsim_topk(corpus.queries, corpus.docs, max(cuts), DIM, corpus.kind), "truth")
        ours, base = _ours(corpus), _staged(corpus)
        for k in cuts:
            wanted = truth.where(F.col("rank") <= k).select("query_id", "doc_id")
            for way, run in (("encodings", ours), ("staged", base)):
                found, took = _timed(run(k, 2 * k))
                rows.append(metrics.recall_at(found, wanted, [k]).select(F.lit(name).alias("corpus"), F.lit(way).alias("way"), F.lit(k).alias("k"), "recall", F.lit(1000 * took / n).alias("ms")))
    return _all(rows)


def comparison_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and largest ratio over corpora of recall and of time, ours to the staged engine's, for the hundred best."""
    rows = compared_over_corpora(spark, sf_dir).where("k = 100")
    ours, base = rows.where("way = 'encodings'"), rows.where("way = 'staged'")
    return _all([metrics.compare(ours, base, m).withColumn("measure", F.lit(m)) for m in ("recall", "ms")])


def evaluated_way(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The evaluated system on items over chunks of trigram vectors: walks over graphs on codes, merged queries re-scored.
    beam, k, recall of the exact k best, milliseconds a query; the staged engine's rows have beam 0."""
    corpus = items_over_chunks(spark, sf_dir, form="trigram")
    corpus = Corpus(store.stored(corpus.queries, "queries"), store.stored(corpus.docs, "bags"), corpus.kind)
    n, k, rows = corpus.queries.count(), 100, []
    truth = store.stored(search.exact_maxsim_topk(corpus.queries, corpus.docs, k, DIM).select("query_id", "doc_id"), "truth")
    params = frontier(10240, DIM)
    shards = max(spark.sparkContext.defaultParallelism, graph.shard_count(corpus.docs.count(), params.width))
    way = Retriever(params, "graph_pq", sample=2000, shards=shards, degree=GRAPH[0], build_beam=GRAPH[1]).fit(corpus.docs)
    base = _staged(corpus)
    runs = [(b, lambda b=b: way.search(corpus.queries, k, b, b, 0.7)) for b in BEAMS if b >= k] + [(0, lambda: base(k, 2 * k))]
    for beam, run in runs:
        found, took = _timed(run())
        rows.append(metrics.recall_at(found, truth, [k]).select(F.lit(beam).alias("beam"), F.col("n").alias("k"), "recall", F.lit(1000 * took / n).alias("ms")))
    return _all(rows)


def latency_bars(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every item over chunks, one at a time through the whole way over a stored index of codes: milliseconds, a Spark
    job's own cost included."""
    corpus = items_over_chunks(spark, sf_dir)
    corpus = Corpus(store.stored(corpus.queries, "queries"), store.stored(corpus.docs, "bags"), corpus.kind)
    way = Retriever(frontier(10240, DIM), "pq", corpus.kind, sample=2000).fit(corpus.docs)
    ids = [r[0] for r in corpus.queries.select("bag_id").orderBy("bag_id").collect()]
    one = lambda i: way.search(corpus.queries.where(F.col("bag_id") == i), 10, 100, tau=0.7).collect()
    one(ids[0])
    got = metrics.latency(one, ids)
    return spark.createDataFrame([(len(ids), *got.values())], "queries int, " + ", ".join(f"{k} double" for k in got))


def throughput(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All items as one batch through the same stored index, by number of candidates: candidates, qps, recall100 of the
    exact hundred best."""
    corpus = items_over_chunks(spark, sf_dir)
    corpus = Corpus(store.stored(corpus.queries, "queries"), store.stored(corpus.docs, "bags"), corpus.kind)
    way = Retriever(frontier(10240, DIM), "pq", corpus.kind, sample=2000).fit(corpus.docs)
    truth = store.stored(search.exact_maxsim_topk(corpus.queries, corpus.docs, 100, DIM, corpus.kind).select("query_id", "doc_id"), "truth")
    n, rows = corpus.queries.count(), []
    for candidates in (100, 200, 500, 1000):
        out: list[DataFrame] = []
        speed = metrics.qps(lambda c=candidates, out=out: out.append(store.stored(way.search(corpus.queries, 100, c, tau=0.7), "found")), n)
        rows.append(metrics.recall_at(out[0], truth, [100]).select(F.lit(candidates).alias("candidates"), F.lit(speed).alias("qps"), F.col("recall").alias("recall100")))
    return _all(rows)


def probe_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the dense best ten and distances computed by routed graph shards: probes, recall, n_dist."""
    rows_of = WL.small_vectors(spark, sf_dir).persist()
    centers = approx.ivf_centers(rows_of, 8)
    built = store.stored(graph.graph_build(rows_of, 1, 16, 32, centers=centers), "graph", "shard")
    queries = rows_of.where("bag_id % 10 = 0")
    exact = search.mips_dense(queries, rows_of, 10, EncodeParams(DIM, 0, DIM, 1)).select("query_id", "doc_id").persist()
    rows = []
    for probes in (1, 2, 4, 8):
        found, cost = graph.graph_search(queries, built, 10, 32, centers, probes)
        per = cost.groupBy("query_id").agg(F.sum("n_dist").alias("d")).agg(F.avg("d").alias("n_dist"))
        rows.append(metrics.recall_at(found, exact, [10]).select(F.lit(probes).alias("probes"), "recall").join(per, F.lit(True)))
    return _all(rows)


def progressive_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the dense best ten by the number of repetitions scored first: first_reps, keep, recall."""
    corpus = items_over_chunks(spark, sf_dir).kept()
    params = frontier(2560, DIM)
    q, d = (x.persist() for x in _encoded(corpus, params))
    exact = search.mips_dense(q, d, 10, params).select("query_id", "doc_id").persist()
    rows = []
    for first in (2, 5, 10):
        one = metrics.recall_at(search.mips_progressive(q, d, 10, params, first, 50), exact, [10])
        rows.append(one.select(F.lit(first).alias("first_reps"), F.lit(50).alias("keep"), "recall"))
    return _all(rows)


def copies(rows: DataFrame, own: DataFrame, k: int = 5) -> DataFrame:
    """The ``k`` best chunks of other documents for each chunk of ``own``. A document's own chunks go inside the scan, so
    however many they are, none takes a candidate's place. Candidates are a share of the chunks, 500 at least."""
    bags, asked = T.bags_of_words(rows), T.bags_of_words(own)
    params, n = frontier(WL.WIDTH, DIM), max(500, -(-rows.count() // WL.SHARE))
    near = search.mips_dense(*_encoded(Corpus(asked, bags, "sign"), params), n, params, owner=10_000_000)
    return search.rerank(near, asked, bags, k, DIM, "sign")


def near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chunks of every hundredth document as queries over all chunks of others: the five best of each."""
    rows = WL.spread(T.numbered_chunks(T.chunks(tables.load(spark, sf_dir, "documents"))))
    return copies(rows, rows.where("doc_id % 100 = 0"))


def rank_fusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two engines' lists merged by reciprocal ranks: a full outer join on query and document."""
    a = WL.mips(spark, sf_dir).select("query_id", "doc_id", F.col("rank").alias("ra"))
    b = WL.token_hit(spark, sf_dir, True).where("rank <= 10").select("query_id", "doc_id", F.col("rank").alias("rb"))
    part = lambda c: F.coalesce(F.lit(1.0) / (F.col(c) + 60), F.lit(0.0))
    return a.join(b, ["query_id", "doc_id"], "full").select("query_id", "doc_id", "ra", "rb", F.round(part("ra") + part("rb"), 9).alias("score"))


def new_owner_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many different documents the raw per-token list holds down to each rank."""
    rows = WL.token_hit(spark, sf_dir, False)
    first = F.row_number().over(W.partitionBy("query_id", "doc_id").orderBy("rank")) == 1
    down = W.partitionBy("query_id").orderBy("rank").rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn("fresh", first.cast("long")).select("query_id", "rank", F.sum("fresh").over(down).alias("owners"))


QUERIES = {
    f.__name__: f
    for f in (
        grid_recall, grid_frontier, text_grid_recall, text_grid_frontier, text_partition_grid, text_candidates_wide, vector_candidates, graph_code_sweep,
        evaluated_way, throughput, partition_comparison, final_map_gain, seed_spread, bag_size_effect, heldout_one_recall, text_one_recall,
        text_candidates, text_floats_scanned, carve_sweep, carve_throughput, code_schemes, compared_over_corpora, comparison_ratios,
        latency_bars, probe_sweep, progressive_sweep, near_copies, rank_fusion, new_owner_curve,
    )
}
