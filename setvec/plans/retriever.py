"""The whole way from bags to ranked documents: encode, index, search, merge close query vectors, re-score.

An index is written once and read by every search after; it can be saved to a folder and loaded by another session.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.operators import approx, graph, search
from setvec.operators.encode import encode_documents, encode_queries
from setvec.plans.params import EncodeParams
from setvec.plans.planner import Choice, choose
from setvec.sources import store

TAU = 0.7
WAYS = ("dense", "progressive", "sparse", "pq", "ivf", "graph", "routed", "graph_pq", "routed_pq")
_SETTINGS = ("kind", "lists", "probes", "codes", "group", "shards", "degree", "build_beam", "first_reps", "keep")


@dataclass
class Retriever:
    """``index``: dense, progressive, sparse, pq, ivf, graph, routed (graph shards by coarse centres), graph_pq and
    routed_pq (the same graphs, built on whole encodings and walked on codes), or auto for the planner's choice. ``kind``
    is the bags' number type.

    ``pq`` scans codes in place of encodings: 256 codes for each 8 numbers by default. ``progressive`` scores
    ``first_reps`` repetitions of all documents and the rest for the ``keep`` of a batch ahead by then and all that a bound
    does not rule out. ``auto`` takes dense, progressive or sparse, whose lists are equal. ``shards``: graphs, or graphs
    for each coarse centre; 0 finds a number that keeps a shard within ``graph.SHARD_BYTES``.
    """

    params: EncodeParams
    index: str = "dense"
    kind: str = "float"
    lists: int = 64
    probes: int = 8
    codes: int = 256
    group: int = 8
    shards: int = 0
    degree: int = 200
    build_beam: int = 600
    first_reps: int | None = None
    keep: int = 1000
    interactive: bool = False
    centers: np.ndarray | None = None
    sample: int = 20_000
    choice: Choice | None = field(default=None, init=False)

    def fit(self, docs: DataFrame, n_queries: int = 1000, store_index: bool = True) -> Retriever:
        """Encodes packed bags and builds the index. Training samples bags and encodes the sample alone; the corpus is
        encoded once, into the stored index. ``store_index=False`` leaves a scan's encodings in the plan, for one search."""
        self.docs = docs
        self.way = self.index
        if self.index == "auto":
            size = docs.agg(F.count("*").alias("n"), F.avg("n").alias("m")).first()
            self.choice = choose(self.params, size["n"], size["m"] or 0.0, n_queries, interactive=self.interactive)
            # Only scans that give the same lists are taken; an index that loses neighbours has to be asked for by name.
            self.way = self.choice.index if self.choice.index in ("dense", "sparse") else "dense"
            if self.way == "dense" and self.choice.first_reps < self.params.reps:
                self.way, self.first_reps = "progressive", self.first_reps or self.choice.first_reps
        if self.way not in WAYS:
            raise ValueError(f"no index named {self.way!r}")
        kept = (lambda df, tag, by=None: store.stored(df, tag, by)) if store_index else (lambda df, tag, by=None: df)
        encoded = encode_documents(docs, self.params, self.centers, self.kind)
        self.book = self.coarse = None
        if self.way in ("pq", "graph_pq", "routed_pq", "ivf", "routed"):
            size = docs.count()
            encoded_sample = store.stored(encode_documents(approx.hash_sample(docs, self.sample, n=size), self.params, self.centers, self.kind), "sample")
            if "pq" in self.way:
                self.book = approx.pq_train(encoded_sample, self.params.width, self.codes, self.group, n=0)
            if self.way in ("ivf", "routed", "routed_pq"):
                self.coarse = approx.ivf_centers(encoded_sample, self.lists, n=0)
        if self.way == "pq":
            self.stored = kept(approx.pq_encode(encoded, self.book), "codes")
        elif self.way == "ivf":
            self.stored = kept(approx.ivf_build(encoded, self.coarse), "lists", "list_id")
        elif self.way in ("dense", "progressive", "sparse"):
            self.stored = kept(encoded, "encodings")
        else:
            if not self.shards:
                per = 1 if self.coarse is None else len(self.coarse)
                self.shards = graph.shard_count(-(-docs.count() // per), self.params.width)
            self.stored = store.stored(graph.graph_build(encoded, self.shards, self.degree, self.build_beam, centers=self.coarse, book=self.book), "graph", "shard")
        return self

    def candidates(self, queries: DataFrame, n: int, beam: int | None = None) -> DataFrame:
        """query_id, rank, doc_id, score by product of encodings."""
        enc = encode_queries(queries, self.params, self.centers, self.kind)
        if self.way == "dense":
            return search.mips_dense(enc, self.stored, n, self.params)
        if self.way == "progressive":
            first = self.first_reps or max(1, self.params.reps // 4)
            return search.mips_progressive(enc, self.stored, n, self.params, first, max(n, self.keep))
        if self.way == "sparse":
            return search.mips_sparse(enc, self.stored, n, self.params)
        if self.way == "pq":
            return approx.pq_search(enc, self.stored, self.book, n)
        if self.way == "ivf":
            return approx.ivf_search(enc, self.stored, self.coarse, n, self.probes)
        return self.walked(queries, n, beam)[0]

    def walked(self, queries: DataFrame, n: int, beam: int | None = None) -> tuple[DataFrame, DataFrame]:
        """Candidates of a graph, and the distances that each query computed in each shard."""
        enc = encode_queries(queries, self.params, self.centers, self.kind)
        return graph.graph_search(enc, self.stored, n, beam or max(n, 64), self.coarse, self.probes, self.shards, self.book)

    def search(self, queries: DataFrame, k: int, candidates: int, beam: int | None = None, tau: float | None = TAU, mode: str = "spread") -> DataFrame:
        """query_id, rank, doc_id, score: candidates in order of MaxSim with the merged query (``tau=None``: whole)."""
        near = self.candidates(queries, candidates, beam)
        return search.rerank(near, queries, self.docs, k, self.params.dim, self.kind, tau, mode)

    def explain(self) -> str:
        return f"{self.choice.explain()}\n  - run: {self.way}" if self.choice else f"index={self.way}"

    def save(self, path: str) -> None:
        """Writes ``path``/settings, /bags, /index, and the codebook and centres where the index has them."""
        spark = self.docs.sparkSession
        told = {"params": self.params.to_json(), "way": self.way, **{name: getattr(self, name) for name in _SETTINGS}}
        book = self.book and {"width": self.book.width, "shape": self.book.centers.shape}
        tables = {"book": (json.dumps(book), self.book.centers if self.book else None), "coarse": (json.dumps(self.coarse is not None and self.coarse.shape), self.coarse), "partition": (json.dumps(self.centers is not None and self.centers.shape), self.centers)}
        rows = [("settings", json.dumps(told), bytearray())] + [(name, form, bytearray(x.astype("<f4").tobytes() if x is not None else b"")) for name, (form, x) in tables.items()]
        by = "list_id" if self.way == "ivf" else "shard" if "shard" in self.stored.columns else None
        self.docs.write.parquet(f"{path}/bags")
        (self.stored.write.partitionBy(by) if by else self.stored.write).parquet(f"{path}/index")
        spark.createDataFrame(rows, "name string, form string, numbers binary").coalesce(1).write.parquet(f"{path}/settings")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Retriever:
        """A saved index, ready for searches."""
        rows = {r["name"]: (json.loads(r["form"]), bytes(r["numbers"])) for r in spark.read.parquet(f"{path}/settings").collect()}
        told = rows["settings"][0]
        way = Retriever(EncodeParams.from_json(told["params"]), told["way"], **{name: told[name] for name in _SETTINGS})
        numbers = lambda name, shape: np.frombuffer(rows[name][1], "<f4").reshape(shape).copy()
        way.way, way.docs, way.stored = told["way"], spark.read.parquet(f"{path}/bags"), spark.read.parquet(f"{path}/index")
        book, coarse, centers = (rows[name][0] for name in ("book", "coarse", "partition"))
        way.book = approx.Codebook(numbers("book", book["shape"]), book["width"]) if book else None
        way.coarse = numbers("coarse", coarse) if coarse else None
        way.centers = numbers("partition", centers) if centers else None
        return way


def roll_up(ranked: DataFrame, owners: DataFrame, k: int) -> DataFrame:
    """Lists of chunks to lists of documents by each document's best chunk. ``owners``: bag_id, doc_id."""
    best = ranked.join(owners.select(F.col("bag_id").alias("chunk"), F.col("doc_id").alias("owner")), F.col("doc_id") == F.col("chunk"))
    best = best.groupBy("query_id", F.col("owner").alias("doc_id")).agg(F.max("score").alias("score"))
    return search.topk(best, k)
