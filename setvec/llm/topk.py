"""Exact top-k by inner product from an impact-ordered index, score at a time.

Components are whole numbers floor(256 x). Every dimension is two terms: a positive query weight meets impacts counted
from the shard's least value up, a negative one impacts counted from its greatest value down, so all impacts are at
least 0 and a score is a constant of the query plus the sum of weight times impact. A shard's index holds, for each
dimension, its rows in order of impact with the segments of each quantised level. Segments are processed for all terms
from the highest levels down; accumulators are lower bounds. After each step a row may be a member only if its bound,
with what its unseen terms can still add, reaches the k-th lower bound; a query stops when this leaves few rows, which
is the proof, and these are scored exactly from the stored vectors. If it never does, the lowest level ends it.

Bounds are exact for components of any size below ``LARGEST``: doubles serve where they hold all sums, wider whole numbers
where they don't.

Shards and blocks of queries meet by the shard's number, so that each task holds one shard and one block of a fixed
size. Ties go to the smaller id. Vectors that are null, empty, or hold null or non-finite components take no part, and a
null id takes none; vectors of different lengths are not compared. Rows that repeat a query's id are its own, so they are no
candidates for it; other repeated rows each are. An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setvec.llm.common import bounded_batches, restored, stored

K, SCALE, EVERY = 5, 256, 50
LEVELS, STEPS = 64, 4
SHARD_ROWS, BLOCK_QUERIES = 4096, 512
#: Components must lie below this in size; larger ones raise an error, as does a score beyond 64 bits.
LARGEST = 1 << 60
#: A query stops once this share of a shard's rows, or fewer, may still be members.
FEW = 1 / 16
INDEX_DDL = "shard int, dim int, ids binary, vectors binary, orders binary, bounds binary"
BLOCK_DDL = "block int, dim int, ids binary, vectors binary"
HIT_DDL = "query_id bigint, vec_id bigint, score bigint"
_INDEX = pa.schema([("shard", pa.int32()), ("dim", pa.int32())] + [(n, pa.binary()) for n in ("ids", "vectors", "orders", "bounds")])
_BLOCK = pa.schema([("block", pa.int32()), ("dim", pa.int32()), ("ids", pa.binary()), ("vectors", pa.binary())])
_HITS = pa.schema([(n, pa.int64()) for n in ("query_id", "vec_id", "score")])


def whole_vectors(rows: DataFrame, column: str = "embedding", key: str = "vec_id") -> DataFrame:
    """vec_id, dim, v: components as floor(SCALE x), rows that take part only."""
    x = F.col(column).cast("array<double>")
    fit = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & (F.size(x) > 0)
    v = F.transform(x, lambda c: F.floor(c * SCALE))
    return rows.where(F.col(key).isNotNull() & F.col(column).isNotNull() & fit).select(F.col(key).cast("long").alias("vec_id"), F.size(x).alias("dim"), v.alias("v"))


def _matrix(table: pa.Table, dim: int) -> np.ndarray:
    return np.concatenate([c.flatten().to_numpy() for c in table.column("v").chunks]).reshape(-1, dim).astype("<i8")


def _index(key: tuple, table: pa.Table) -> pa.Table:
    """A shard's row: ids, vectors, for each dimension its rows from the largest component down, and where each level
    of the quantised components ends in that order."""
    shard, dim = (k.as_py() for k in key)
    v = _matrix(table, dim)
    low, high = v.min(0), v.max(0)
    if int(high.max()) >= LARGEST or int(low.min()) < -LARGEST:
        raise ValueError(f"components beyond {LARGEST} have no scores that fit 64 bits")
    width = np.maximum(1, -(-(high - low + 1) // LEVELS))
    level = (v - low) // width
    order = np.argsort(-v, axis=0, kind="stable")
    ends = np.stack([np.searchsorted(-level[order[:, d], d], -np.arange(LEVELS), side="right") for d in range(dim)])
    ids = table.column("vec_id").to_numpy().astype("<i8")
    row = [[shard], [dim], [ids.tobytes()], [v.tobytes()], [order.T.astype("<i4").tobytes()], [ends.astype("<i4").tobytes()]]
    return pa.table([pa.array(x, f.type) for x, f in zip(row, _INDEX, strict=True)], schema=_INDEX)


def build_index(vectors: DataFrame, shard_rows: int = SHARD_ROWS) -> tuple[DataFrame, int]:
    """The index, a row per shard and dimension count, and the number of shards."""
    bounded_batches(vectors.sparkSession)
    shards = max(1, -(-vectors.count() // shard_rows))
    rows = vectors.withColumn("shard", F.pmod(F.xxhash64("vec_id", "v"), F.lit(shards)).cast("int"))
    return stored(rows.groupBy("shard", "dim").applyInArrow(_index, INDEX_DDL), "index"), shards


def query_blocks(queries: DataFrame, size: int = BLOCK_QUERIES) -> DataFrame:
    def pack(key: tuple, table: pa.Table) -> pa.Table:
        block, dim = (k.as_py() for k in key)
        ids = table.column("vec_id").to_numpy().astype("<i8")
        row = [[block], [dim], [ids.tobytes()], [_matrix(table, dim).tobytes()]]
        return pa.table([pa.array(x, f.type) for x, f in zip(row, _BLOCK, strict=True)], schema=_BLOCK)

    blocks = max(1, -(-queries.count() // size))
    rows = queries.withColumn("block", F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks)).cast("int"))
    return rows.groupBy("block", "dim").applyInArrow(pack, BLOCK_DDL)


def number_type(q: np.ndarray, v: np.ndarray) -> type:
    """What holds every bound of a shard exactly: doubles below 2^52, 64-bit numbers below 2^62, else Python's own."""
    most = lambda x: max(int(x.max(initial=0)), -int(x.min(initial=0)))
    top = most(q) * (2 * most(v) + 2 * LEVELS) * 2 * v.shape[1]
    return np.float64 if top < 1 << 52 else np.int64 if top < 1 << 62 else object


class Shard:
    """A shard's index in memory. The segments of one step are opened at a time, as a matrix of terms by rows."""

    def __init__(self, dim: int, ids: bytes, vectors: bytes, orders: bytes, bounds: bytes):
        self.ids = np.frombuffer(ids, "<i8")
        self.v = np.frombuffer(vectors, "<i8").reshape(-1, dim)
        self.low, self.high = self.v.min(0), self.v.max(0)
        self.width = np.maximum(1, -(-(self.high - self.low + 1) // LEVELS))
        self.top = self.low + LEVELS * self.width - 1
        self.order = np.frombuffer(orders, "<i4").reshape(dim, -1)
        self.ends = np.frombuffer(bounds, "<i4").reshape(dim, LEVELS)

    def segments(self, high: int, low: int, kind: type) -> tuple[np.ndarray, np.ndarray]:
        """Impacts of the levels from ``high`` (exclusive) down to ``low``, and which rows they are of: the rising terms
        of all dimensions, then the falling ones."""
        dim, n = self.order.shape
        impact, seen = np.zeros((2 * dim, n), kind), np.zeros((2 * dim, n), kind)
        for d in range(dim):
            # ends[d, l] is where level l ends in the order from large to small
            a, b = (0 if high == LEVELS else self.ends[d, high]), self.ends[d, low]
            rows = self.order[d, a:b]
            impact[d, rows] = (self.v[rows, d] - self.low[d]) // self.width[d] * self.width[d]
            seen[d, rows] = 1
            a = 0 if low == 0 else self.ends[d, LEVELS - low]
            rows = self.order[d, a : self.ends[d, LEVELS - high]]
            impact[dim + d, rows] = (self.top[d] - self.v[rows, d]) // self.width[d] * self.width[d]
            seen[dim + d, rows] = 1
        return impact, seen

    def search(self, ids: np.ndarray, q: np.ndarray, k: int) -> Iterator[tuple[int, int, int]]:
        """(query, row, score) of each query's k best rows. All bounds are whole numbers, held exactly."""
        kind = number_type(q, self.v)
        pos, neg = np.maximum(q, 0).astype(kind), np.maximum(-q, 0).astype(kind)
        weights, width = np.concatenate([pos, neg], 1), np.concatenate([self.width, self.width]).astype(kind)
        base = pos @ self.low.astype(kind) - neg @ self.top.astype(kind)
        live = np.arange(len(q))
        acc = np.repeat(base[:, None], len(self.ids), axis=1)
        seen, all_seen = np.zeros_like(acc), weights @ width
        own = ids[:, None] == self.ids
        nothing = -np.inf if kind is np.float64 else -(1 << 63) if kind is np.int64 else -(1 << 200)
        few = max(4 * k, int(FEW * len(self.ids)))
        for high in range(LEVELS, 0, -LEVELS // STEPS):
            low = high - LEVELS // STEPS
            impact, here = self.segments(high, low, kind)
            own_weights = weights[live]
            acc = acc + own_weights @ impact
            seen = seen + (own_weights * width) @ here
            # A seen impact is below its level's start plus the width, an unseen one below the step's lowest start.
            slack = seen - own_weights.sum(1)[:, None] + low * (all_seen[live][:, None] - seen)
            bound = np.where(own[live], nothing, acc)
            floor = np.sort(bound, axis=1)[:, -k] if kind is object else np.partition(bound, -k, axis=1)[:, -k] if len(self.ids) >= k else np.full(len(acc), nothing)
            maybe = (acc + slack >= floor[:, None]) & ~own[live]
            done = (maybe.sum(1) <= few) | (low == 0)
            for r in np.flatnonzero(done):
                rows = np.flatnonzero(maybe[r])
                score = self.v[rows].astype(object if kind is object else np.int64) @ q[live[r]].astype(object if kind is object else np.int64)
                best = sorted(range(len(rows)), key=lambda i: (-score[i], self.ids[rows[i]]))[:k] if kind is object else np.lexsort((self.ids[rows], -score))[:k]
                for b in best:
                    yield int(ids[live[r]]), int(self.ids[rows[b]]), int(score[b])
            live, acc, seen = live[~done], acc[~done], seen[~done]
            if not len(live):
                return


def topk(index: DataFrame, shards: int, blocks: DataFrame, k: int = K) -> DataFrame:
    """query_id, rank, vec_id, score. Each shard gets every block of queries by an equi-join on its number; a task keeps
    the shard it has open, gives k rows a query and shard, and these meet in a top-k by query."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opened: tuple | None = None
        for batch in batches:
            for i in range(batch.num_rows):
                r = {c: batch.column(c)[i].as_py() for c in ("shard", "dim", "q_ids", "q_vectors")}
                if opened is None or opened[0] != (r["shard"], r["dim"]):
                    parts = (batch.column(c)[i].as_py() for c in ("ids", "vectors", "orders", "bounds"))
                    opened = (r["shard"], r["dim"]), Shard(r["dim"], *parts)
                q = np.frombuffer(r["q_vectors"], "<i8").reshape(-1, r["dim"])
                hits = list(opened[1].search(np.frombuffer(r["q_ids"], "<i8"), q, k))
                if hits:
                    yield pa.record_batch([pa.array(c, pa.int64()) for c in zip(*hits, strict=True)], schema=_HITS)

    spread = blocks.select(
        F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), "dim", F.col("ids").alias("q_ids"), F.col("vectors").alias("q_vectors")
    )
    # A joined row holds a whole shard: few rows to a batch keep it bounded. Blocks look small before they are dealt to all
    # shards, so the join is told not to send them through the driver.
    before = bounded_batches(index.sparkSession, 4)
    try:
        hits = stored(index.join(spread.hint("merge"), ["shard", "dim"]).mapInArrow(run, HIT_DDL), "hits")
    finally:
        restored(index.sparkSession, before)
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return hits.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op2_impact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = stored(whole_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "vectors")
    index, shards = build_index(vectors)
    return topk(index, shards, query_blocks(vectors.where(F.col("vec_id") % EVERY == 0)))


OP2_SQL = f"""
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(x::DOUBLE * {SCALE})::BIGINT) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % {EVERY} = 0),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM scored)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= {K}
"""
