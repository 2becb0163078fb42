"""Approximate product search: product quantisation and inverted lists.

Training runs inside tasks, a group at a time, on samples of stated sizes. What
reaches the driver is a codebook or a table of centres, whose size hangs on the settings and not on the corpus.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setvec.functions import seeds, vectors
from setvec.operators import kernels
from setvec.operators.search import Best, query_blocks, topk
from setvec.sources.store import bounded_bytes

HITS = "query_id bigint, doc_id bigint, score double"
FIXED_HITS = "query_id bigint, doc_id bigint, score bigint"
#: Queries of a block that are scored by tables at most; more are scored by decoding. Bytes that are decoded at once.
BY_TABLE, DECODED_BYTES = 4, 16 << 20
#: Queries and documents of a block in the form by joins, documents whose sums are held at once, bytes of joined blocks in a
#: batch.
BLOCK_QUERIES, BLOCK_DOCS, MEETING_DOCS, MEETING_BYTES = 64, 1 << 16, 1 << 12, 16 << 20
#: Bytes of encodings that coarse centres are trained on, in one task.
CENTER_BYTES = 256 << 20
#: Rows of floats that are coded at once.
ENCODED_ROWS = 256


def floats(raw: pa.Array, kind: str = "float") -> np.ndarray:
    rows = [np.frombuffer(x, vectors.KINDS[kind]) for x in raw.to_pylist()]
    return np.stack(rows) if rows else np.zeros((0, 0), vectors.KINDS[kind])


def hash_sample(rows: DataFrame, size: int, seed: int = 42, purpose: str = "pqinit", n: int | None = None) -> DataFrame:
    """About ``size`` rows, the same ones on every run: those whose hash of the id is low. ``n``: how many rows there are,
    where that is known; else they are counted, so bags are sampled and not their encodings."""
    n = max(1, rows.count() if n is None else n)
    part = F.pmod(F.xxhash64(F.lit(f"{purpose}:{seed}"), "bag_id"), F.lit(1 << 20))
    return rows.where(part < int(min(1.0, size / n) * (1 << 20)) + 1)


# --- product quantisation -----------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Codebook:
    """Centres (groups, codes, group size) of consecutive runs of coordinates."""

    centers: np.ndarray
    width: int

    @property
    def group(self) -> int:
        return self.centers.shape[2]

    @property
    def code_bytes(self) -> int:
        return self.centers.shape[0] if self.centers.shape[1] > 16 else -(-self.centers.shape[0] // 2)

    @cached_property
    def _longer(self) -> np.ndarray:
        """Twice the centres and their squared lengths' negatives (groups, group size + 1, codes)."""
        return np.concatenate([2 * self.centers.transpose(0, 2, 1), -np.einsum("gcd,gcd->gc", self.centers, self.centers)[:, None]], 1)

    def encode(self, x: np.ndarray) -> np.ndarray:
        """Bytes (rows, code_bytes): a byte a group, or two groups a byte for up to 16 codes."""
        parts = _grouped(x, self.group)
        code = np.empty((len(x), len(self.centers)), np.uint8)
        if x.dtype.kind == "f":
            # The centres' lengths are one more coordinate of the product, and a slice of rows stays in a core's cache.
            groups, codes, size = self.centers.shape
            score = np.empty((ENCODED_ROWS, codes), np.float32)
            for a in range(0, len(x), ENCODED_ROWS):
                rows = np.ones((groups, len(parts[a : a + ENCODED_ROWS]), size + 1), np.float32)
                rows[:, :, :-1] = parts[a : a + ENCODED_ROWS].transpose(1, 0, 2)
                for g in range(groups):
                    code[a : a + ENCODED_ROWS, g] = np.matmul(rows[g], self._longer[g], out=score[: rows.shape[1]]).argmax(1)
        else:
            for g in range(len(self.centers)):
                code[:, g] = kernels.nearest_center(parts[:, g], self.centers[g])
        if self.centers.shape[1] > 16:
            return code
        if code.shape[1] % 2:
            code = np.concatenate([code, np.zeros((len(code), 1), np.uint8)], 1)
        return code[:, ::2] | code[:, 1::2] << 4

    def unpacked(self, raw: np.ndarray) -> np.ndarray:
        if self.centers.shape[1] > 16:
            return raw
        return np.stack([raw & 15, raw >> 4], 2).reshape(len(raw), -1)[:, : len(self.centers)]

    def decode(self, raw: np.ndarray) -> np.ndarray:
        code = self.unpacked(raw)
        at = np.arange(len(self.centers), dtype=np.int32) * self.centers.shape[1]
        return self.centers.reshape(-1, self.group).take(code + at, axis=0).reshape(len(code), -1)[:, : self.width]

    def table(self, query: np.ndarray) -> np.ndarray:
        """Products of an uncompressed query's groups with all centres (groups, codes)."""
        return np.einsum("gcd,gd->gc", self.centers, _grouped(query[None], self.group)[0])

    def distances(self, query: np.ndarray, codes: np.ndarray):
        """Negative scores of rows of ``codes`` by one look-up table of an uncompressed query."""
        flat, at = self.table(query).ravel(), np.arange(len(self.centers)) * self.centers.shape[1]
        return lambda rows: -flat[codes[rows] + at].sum(1)

    def score(self, table: np.ndarray, code: np.ndarray) -> np.ndarray:
        flat, at = table.ravel(), np.arange(len(self.centers)) * self.centers.shape[1]
        return flat[code + at].sum(1)


def _grouped(x: np.ndarray, group: int) -> np.ndarray:
    over = -x.shape[1] % group
    padded = np.concatenate([x, np.zeros((len(x), over), x.dtype)], 1) if over else x
    return padded.reshape(len(x), -1, group)


def pq_train(encodings: DataFrame, width: int, codes: int = 256, group: int = 8, rounds: int = 4, sample: int = 20_000, seed: int = 42, n: int | None = None) -> Codebook:
    """A codebook from a hash sample of at most about ``sample`` encodings; every group of coordinates is trained in a
    task of its own. With fewer distinct runs than codes each becomes a centre, and nothing is lost. ``n``: the number
    of encodings, 0 if they are a sample already."""
    if not 1 < codes <= 256:
        raise ValueError("2 to 256 codes")
    rows = encodings if n == 0 else hash_sample(encodings, sample, seed, n=n)
    return pq_train_schemes(rows, width, [(codes, group)], rounds, seed)[0]


def pq_train_schemes(encodings: DataFrame, width: int, schemes: list[tuple[int, int]], rounds: int = 4, seed: int = 42) -> list[Codebook]:
    """Codebooks of several schemes (codes, group) on one sample of encodings, which is shuffled once: a task has a run of
    coordinates and trains all schemes' groups in it."""
    base = int(np.lcm.reduce([group for _, group in schemes]))
    run = base * max(1, -(-width // base) // 64)

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                parts = _grouped(floats(batch.column("enc")), run)
                for g in range(parts.shape[1]):
                    raw = [x.astype("<f4").tobytes() for x in parts[:, g]]
                    yield pa.record_batch([pa.array([g] * len(raw), pa.int32()), pa.array(raw, pa.binary())], names=["g", "part"])

    def train(key, rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        points = np.stack([np.frombuffer(x, "<f4") for x in rows["part"]])
        for scheme, (codes, group) in enumerate(schemes):
            first = int(key[0]) * (run // group)
            for i in range(first, min(first + run // group, -(-width // group))):
                distinct, count = np.unique(points[:, (i - first) * group : (i - first + 1) * group], axis=0, return_counts=True)
                if len(distinct) <= codes:
                    centers = np.concatenate([distinct, np.repeat(distinct[:1], codes - len(distinct), 0)])
                else:
                    start = seeds.generator("pqinit", seed, i).permutation(len(distinct))[:codes]
                    centers = kernels.lloyd(distinct, distinct[np.sort(start)], rounds, count.astype(np.float64))
                out.append((scheme, i, centers.astype("<f4").tobytes()))
        return pd.DataFrame(out, columns=["scheme", "group_id", "centers"])

    rows = encodings.select("enc").mapInArrow(explode, "g int, part binary")
    found = rows.groupBy("g").applyInPandas(train, "scheme int, group_id int, centers binary").orderBy("scheme", "group_id").collect()
    return [Codebook(np.stack([np.frombuffer(r["centers"], "<f4").reshape(codes, group) for r in found if r["scheme"] == at]), width) for at, (codes, group) in enumerate(schemes)]


def pq_encode(encodings: DataFrame, book: Codebook, kind: str = "float") -> DataFrame:
    """bag_id, code."""
    shared = encodings.sparkSession.sparkContext.broadcast(book)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                code = shared.value.encode(floats(batch.column("enc"), kind))
                yield pa.record_batch([batch.column("bag_id"), pa.array([x.tobytes() for x in code], pa.binary())], names=["bag_id", "code"])

    return encodings.select("bag_id", "enc").mapInArrow(run, "bag_id bigint, code binary")


def pq_decode(codes: DataFrame, book: Codebook) -> DataFrame:
    """bag_id, enc: the centres that the codes name."""
    shared = codes.sparkSession.sparkContext.broadcast(book)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                raw = np.stack([np.frombuffer(x, np.uint8) for x in batch.column("code").to_pylist()])
                enc = [x.astype("<f4").tobytes() for x in shared.value.decode(raw)]
                yield pa.record_batch([batch.column("bag_id"), pa.array(enc, pa.binary())], names=["bag_id", "enc"])

    return codes.select("bag_id", "code").mapInArrow(run, "bag_id bigint, enc binary")


def pq_search(query_enc: DataFrame, codes: DataFrame, book: Codebook, k: int, kind: str = "float") -> DataFrame:
    """Top ``k`` codes; the query stays uncompressed. A few queries are scored by their look-up tables, a row of codes a
    few hundred look-ups; more than ``BY_TABLE`` share the decoding of a slice of codes and one product, which adds the
    same terms. In whole numbers both give the same scores; in floats they differ in rounding alone."""
    fixed = kind == "fixed"
    ddl = FIXED_HITS if fixed else HITS
    out = None
    for block in query_blocks(query_enc, "enc"):
        shared = codes.sparkSession.sparkContext.broadcast(([(r["bag_id"], bytes(r["enc"])) for r in block], book))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            rows, own = shared.value
            best = Best(len(rows), k)
            queries = np.stack([np.frombuffer(x, vectors.KINDS[kind]) for _, x in rows])
            tables = [own.table(x) for x in queries] if len(rows) <= BY_TABLE else None
            step = max(1, DECODED_BYTES // (4 * own.width))
            for batch in batches:
                raw = [np.frombuffer(x, np.uint8) for x in batch.column("code").to_pylist()]
                ids = batch.column("bag_id").to_numpy()
                for a in range(0, batch.num_rows, step):
                    part, names = np.stack(raw[a : a + step]), ids[a : a + step]
                    if tables is not None:
                        code = own.unpacked(part)
                        scores = np.stack([own.score(t, code) for t in tables])
                    else:
                        scores = queries @ own.decode(part).T
                    best.add_all(names, scores)
            yield best.rows([q for q, _ in rows], fixed)

        hits = codes.select("bag_id", "code").mapInArrow(run, ddl)
        out = hits if out is None else out.union(hits)
    return topk(out if out is not None else codes.sparkSession.createDataFrame([], ddl), k)


def pq_search_by_joins(queries: DataFrame, codes: DataFrame, centers: DataFrame, group: int, k: int) -> DataFrame:
    """The same by joins, from rows (query_id, dim, x), (doc_id, g, code) and (code, dim, center). A query's products with
    all centres are summed by group first; blocks of documents meet blocks of these sums by a join on the block's number,
    and a pair of blocks gives its queries' ``k`` best, so no pair of a query and a document becomes a row. The centres are
    a codebook, whose size hangs on the settings alone."""
    spark = codes.sparkSession
    bounded_bytes(spark, MEETING_BYTES)
    blocks = lambda rows, key, size: max(1, -(-rows.agg(F.count_distinct(key)).first()[0] // size))
    n_query, n_doc = blocks(queries, "query_id", BLOCK_QUERIES), blocks(codes, "doc_id", BLOCK_DOCS)
    dealt = lambda rows, key, n: rows.withColumn("block", F.pmod(F.xxhash64(key), F.lit(n)).cast("int"))

    def packed(rows: DataFrame, owner: str, number: str, kind: str, names: tuple[str, ...]) -> DataFrame:
        """A row for each block: its ids, and for each id its numbers in order of group and code."""

        def pack(key: tuple, table: pa.Table) -> pa.Table:
            ids, at = np.unique(table[owner].to_numpy(), return_inverse=True)
            order = np.lexsort([*(table[c].to_numpy() for c in reversed(names)), at])
            numbers = table[number].to_numpy()[order].astype(kind)
            return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "ids": [ids.astype("<i8").tobytes()], "numbers": [numbers.tobytes()]})

        return rows.groupBy("block").applyInArrow(pack, "block int, ids binary, numbers binary")

    # Dealt by block before they meet the centres, so that neither the sums nor the packing shuffle again.
    asked = dealt(queries, "query_id", n_query).repartition("block")
    sums = asked.join(F.broadcast(centers), "dim").groupBy("block", "query_id", F.floor(F.col("dim") / group).cast("int").alias("g"), "code")
    sums = packed(sums.agg(F.sum(F.col("x") * F.col("center")).alias("part")), "query_id", "part", "<f8", ("g", "code"))
    own = packed(dealt(codes, "doc_id", n_doc), "doc_id", "code", "<i4", ("g",)).select(F.col("ids").alias("doc_ids"), F.col("numbers").alias("codes"))
    spread = own.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(n_query - 1))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                names, docs = (np.frombuffer(batch.column(c)[i].as_py(), "<i8") for c in ("ids", "doc_ids"))
                code = np.frombuffer(batch.column("codes")[i].as_py(), "<i4").reshape(len(docs), -1)
                part = np.frombuffer(batch.column("numbers")[i].as_py(), "<f8").reshape(len(names), code.shape[1], -1)
                best = Best(len(names), k)
                for a in range(0, len(docs), MEETING_DOCS):
                    own = code[a : a + MEETING_DOCS]
                    best.add_all(docs[a : a + MEETING_DOCS], sum(part[:, g][:, own[:, g]] for g in range(code.shape[1])))
                yield best.rows(names.tolist(), False)

    return topk(sums.hint("merge").join(spread, "block").select("ids", "numbers", "doc_ids", "codes").mapInArrow(run, HITS), k)


# --- inverted lists -----------------------------------------------------------------------------------------------


def ivf_centers(encodings: DataFrame, lists: int, rounds: int = 5, sample: int = 20_000, seed: int = 42, n: int | None = None) -> np.ndarray:
    """Coarse centres, trained in one task on a hash sample of at most ``sample`` rows and ``CENTER_BYTES``; only the
    centres reach the driver. ``n``: as for ``pq_train``."""
    rows = encodings if n == 0 else hash_sample(encodings, sample, seed, "center", n)

    def train(table: pa.Table) -> pa.Table:
        order = sorted(range(table.num_rows), key=lambda i: (table["h"][i].as_py(), table["bag_id"][i].as_py()))
        first = table["enc"][order[0]].as_py() if order else b""
        order = order[: min(sample, max(lists, CENTER_BYTES // max(1, len(first))))]
        points = floats(table.take(order)["enc"].combine_chunks())
        centers = kernels.lloyd(points, points[: min(lists, len(points))], rounds) if len(points) else np.zeros((0, 0), "<f4")
        return pa.table({"c": pa.array(range(len(centers)), pa.int32()), "center": pa.array([x.astype("<f4").tobytes() for x in centers], pa.binary())})

    keyed = rows.select(F.lit(0).alias("all"), "bag_id", "enc", F.xxhash64(F.lit(seed), "bag_id").alias("h"))
    found = keyed.groupBy("all").applyInArrow(train, "c int, center binary").orderBy("c").collect()
    return np.stack([np.frombuffer(r["center"], "<f4") for r in found])


def ivf_build(encodings: DataFrame, centers: np.ndarray) -> DataFrame:
    """bag_id, enc, list_id: the centre of the largest product after lengths are taken off (2 x.c - c.c)."""
    shared = encodings.sparkSession.sparkContext.broadcast(centers)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                code = kernels.nearest_center(floats(batch.column("enc")), shared.value)
                yield pa.record_batch([batch.column("bag_id"), batch.column("enc"), pa.array(code.astype(np.int32))], names=["bag_id", "enc", "list_id"])

    return encodings.select("bag_id", "enc").mapInArrow(run, "bag_id bigint, enc binary, list_id int")


def ivf_search(query_enc: DataFrame, index: DataFrame, centers: np.ndarray, k: int, probes: int) -> DataFrame:
    """Top ``k`` within the ``probes`` lists of the largest product with a query. Written with ``partitionBy(list_id)``,
    an index is read only in the probed lists. With all lists probed this is the exact scan."""
    spark = index.sparkSession
    out = None
    for block in query_blocks(query_enc, "enc"):
        rows = [(r["bag_id"], bytes(r["enc"])) for r in block]
        product = np.stack([np.frombuffer(x, "<f4") for _, x in rows]) @ centers.T
        near = np.argsort(-product, axis=1, kind="stable")[:, :probes]
        wanted = [int(x) for x in np.unique(near)]
        shared = spark.sparkContext.broadcast((rows, [set(x.tolist()) for x in near]))

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            own, lists = shared.value
            best = Best(len(own), k)
            queries = np.stack([np.frombuffer(x, "<f4") for _, x in own])
            wanted_by: dict[int, list[int]] = {}
            for q, near in enumerate(lists):
                for x in near:
                    wanted_by.setdefault(x, []).append(q)
            for batch in batches:
                enc, ids, of = floats(batch.column("enc")), batch.column("bag_id").to_numpy(), batch.column("list_id").to_numpy()
                for x in np.unique(of).tolist():
                    here, asked = np.flatnonzero(of == x), wanted_by.get(x, [])
                    if asked:
                        best.add_all(ids[here], (queries[asked] @ enc[here].T).astype(np.float64), asked)
            yield best.rows([q for q, _ in own], False)

        hits = index.where(F.col("list_id").isin(wanted)).select("bag_id", "enc", "list_id").mapInArrow(run, HITS)
        out = hits if out is None else out.union(hits)
    return topk(out if out is not None else spark.createDataFrame([], HITS), k)
