"""Product search by walks over bounded-degree proximity graphs, a graph for each shard.

A shard is one row: ids, links and the nodes' points, or their codes in place of points. Graphs are built on
uncompressed encodings; a walk may run on codes, with the query left uncompressed. Shards are read where they lie: a
search is one pass over the rows of the shards that it wants, without a shuffle of the index.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setvec.functions import seeds, vectors
from setvec.operators.approx import Codebook, ivf_build
from setvec.operators.search import query_blocks, topk
from setvec.sources.store import bounded_bytes

#: Bytes of uncompressed encodings that one shard is built on, in one task.
SHARD_BYTES = 256 << 20
#: Bytes of a shard's table of distances, beyond which they are worked out as they are needed.
TABLE_BYTES = 512 << 20
#: Rows of that table that are worked out at once.
SLICE_ROWS = 256
_SHARD = pa.schema(
    [("shard", pa.int32()), ("n", pa.int32()), ("entry", pa.int32()), ("ids", pa.binary()), ("links", pa.binary()), ("points", pa.binary())]
)
SHARD_DDL = "shard int, n int, entry int, ids binary, links binary, points binary"
WALKED = "query_id bigint, shard int, n_dist bigint, hits array<struct<doc_id:bigint,score:{0}>>"


def shard_count(n: int, width: int) -> int:
    """Shards for ``n`` nodes so that none is built on more than about ``SHARD_BYTES``."""
    return max(1, -(-n * width * 4 // SHARD_BYTES))


def walk(far: Callable[[np.ndarray], np.ndarray], links: np.ndarray, entry: int, beam: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Nearest first from the entry: the seen nodes in order of distance, their distances, and how many were computed. A
    node is left unvisited once ``beam`` seen ones are nearer."""
    seen = np.zeros(len(links), bool)
    seen[entry] = True
    first = far(np.array([entry]))[0]
    nodes, costs = [entry], [first]
    ahead, best = [(first, entry)], [-first]
    while ahead:
        cost, node = heapq.heappop(ahead)
        if len(best) >= beam and cost > -best[0]:
            break
        new = links[node]
        new = new[new >= 0]
        new = new[~seen[new]]
        if not len(new):
            continue
        seen[new] = True
        for x, c in zip(new.tolist(), far(new).tolist(), strict=True):
            nodes.append(x)
            costs.append(c)
            if len(best) < beam or c <= -best[0]:
                heapq.heappush(ahead, (c, x))
                (heapq.heappush if len(best) < beam else heapq.heappushpop)(best, -c)
    ids, cost = np.array(nodes), np.array(costs)
    order = np.lexsort((ids, cost))
    return ids[order], cost[order], len(nodes)


class Distances:
    """Squared distances between the rows of an array: all at once from one product where they fit ``TABLE_BYTES``, else
    worked out for the rows that are asked for."""

    def __init__(self, points: np.ndarray):
        self.points = points
        self.square = np.concatenate([(points[a : a + SLICE_ROWS].astype(np.float64) ** 2).sum(1) for a in range(0, len(points), SLICE_ROWS)] or [np.zeros(0)])
        self.all = None
        if len(points) ** 2 * 4 <= TABLE_BYTES:
            self.all = np.empty((len(points), len(points)), np.float32)
            # By slices, as sums in doubles take several times the table.
            for a in range(0, len(points), SLICE_ROWS):
                b = a + SLICE_ROWS
                self.all[a:b] = np.maximum(0, self.square[a:b, None] + self.square - 2.0 * (points[a:b] @ points.T))

    def of(self, node: int, rows: np.ndarray) -> np.ndarray:
        if self.all is not None:
            return self.all[node, rows]
        return np.maximum(0, self.square[rows] + self.square[node] - 2.0 * (self.points[rows] @ self.points[node])).astype(np.float32)

    def among(self, rows: np.ndarray) -> np.ndarray:
        if self.all is not None:
            return self.all[np.ix_(rows, rows)]
        own = self.points[rows]
        return np.maximum(0, self.square[rows][:, None] + self.square[rows] - 2.0 * (own @ own.T)).astype(np.float32)


def _pruned(near: Distances, node: int, pool: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Neighbours in order of distance, each kept unless one kept before lies much closer to it than the node does."""
    pool = np.unique(pool[(pool != node) & (pool >= 0)])
    far = near.of(node, pool)
    order = np.lexsort((pool, far))
    pool, far = pool[order], far[order]
    between = alpha * near.among(pool)
    alive, kept = np.ones(len(pool), bool), []
    for i in range(len(pool)):
        if alive[i]:
            kept.append(pool[i])
            if len(kept) == degree:
                break
            alive &= between[i] > far
    return np.array(kept, np.int64)


def _reach_all(links: np.ndarray, entry: int) -> None:
    """Links every lost node from a reached one, over room or over a link that no first visit used; so a reached node is
    never lost again and each step reaches at least one more."""
    n = len(links)
    parent = np.full(n, -1)
    parent[entry] = entry
    stack, hosts = [entry], []

    def visit() -> None:
        while stack:
            node = stack.pop()
            hosts.append(node)
            for x in links[node].tolist():
                if x >= 0 and parent[x] < 0:
                    parent[x] = node
                    stack.append(x)

    visit()
    while len(lost := np.flatnonzero(parent < 0)):
        host = hosts[-1]
        spare = np.flatnonzero((links[host] < 0) | (parent[links[host]] != host))
        if not len(spare):
            hosts.pop()
            continue
        links[host, spare[-1]] = lost[0]
        parent[lost[0]] = host
        stack.append(int(lost[0]))
        visit()


def build_links(points: np.ndarray, degree: int, beam: int, alpha: float, seed: int) -> tuple[np.ndarray, int]:
    """Out-links of each node (-1 where there are fewer than ``degree``) and the entry. Lengths are completed by one
    coordinate, so that near means a large product."""
    return linked(completed(np.concatenate([points, np.zeros((len(points), 1), points.dtype)], 1)), degree, beam, alpha, seed)


def completed(full: np.ndarray) -> np.ndarray:
    """Fills the last coordinate, in place, so that all rows have one length."""
    square = np.concatenate([(full[a : a + SLICE_ROWS, :-1] ** 2).sum(1) for a in range(0, len(full), SLICE_ROWS)] or [np.zeros(0, full.dtype)])
    full[:, -1] = np.sqrt(np.maximum(0, square.max(initial=0) - square))
    return full


def linked(full: np.ndarray, degree: int, beam: int, alpha: float, seed: int) -> tuple[np.ndarray, int]:
    """``build_links`` of points whose lengths are completed."""
    n = len(full)
    if degree < 2:
        raise ValueError("degree is at least 2")
    near = Distances(full)
    rng = seeds.generator("shard", seed)
    links = np.full((n, degree), -1, np.int32)
    for i in range(n if n > 1 else 0):
        drawn = rng.choice(n, min(degree, n - 1), replace=False)
        drawn = drawn[drawn != i]
        links[i, : len(drawn)] = drawn
    middle = full.mean(0)
    entry = int(np.concatenate([((full[a : a + SLICE_ROWS] - middle) ** 2).sum(1) for a in range(0, n, SLICE_ROWS)]).argmin())
    for node in rng.permutation(n):
        seen, _, _ = walk(lambda x, node=node: near.of(node, x), links, entry, beam)
        kept = _pruned(near, node, np.concatenate([seen[: 2 * beam], links[node]]), degree, alpha)
        links[node] = -1
        links[node, : len(kept)] = kept
        for other in kept.tolist():
            own = links[other]
            if node in own:
                continue
            room = np.flatnonzero(own < 0)
            if len(room):
                own[room[0]] = node
            else:
                pool = _pruned(near, other, np.append(own, node), degree, alpha)
                own[:] = -1
                own[: len(pool)] = pool
    _reach_all(links, entry)
    return links, entry


def graph_build(
    encodings: DataFrame, shards: int = 1, degree: int = 200, build_beam: int = 600, alpha: float = 1.2, seed: int = 42,
    centers: np.ndarray | None = None, kind: str = "float", book: Codebook | None = None,
) -> DataFrame:
    """A row for each shard, its graph built on uncompressed encodings in one task (``shard_count`` bounds its bytes). With
    ``book`` the task writes the nodes' codes in place of their points, so no row holds a shard's encodings.

    With coarse ``centers`` (``ivf_centers``) the nodes nearest to one centre share ``shards`` shards, so that a search
    can be routed, and ``shards`` splits the centre that most nodes hang on.
    """

    shared = None if book is None else encodings.sparkSession.sparkContext.broadcast(book)

    def build(key: tuple, table: pa.Table) -> pa.Table:
        table = table.sort_by("bag_id")
        ids = table["bag_id"].to_numpy().astype("<i8")
        raw = b"".join(x.as_py() for x in table["enc"])
        own = np.frombuffer(raw, vectors.KINDS[kind]).reshape(len(ids), -1)
        links, entry = build_links(own.astype(np.float64 if kind == "fixed" else np.float32), degree, build_beam, alpha, seed)
        if shared is not None:
            raw = coded(own, shared.value)
        row = [[key[0].as_py()], [len(ids)], [entry], [ids.tobytes()], [links.astype("<i4").tobytes()], [raw]]
        return pa.table([pa.array(x, f.type) for x, f in zip(row, _SHARD, strict=True)], schema=_SHARD)

    dealt = F.pmod(F.xxhash64(F.lit(f"shard:{seed}"), "bag_id"), F.lit(shards)).cast("int")
    if centers is not None:
        encodings, dealt = ivf_build(encodings, centers), F.col("list_id") * shards + dealt
    return encodings.select("bag_id", "enc", dealt.alias("shard")).groupBy("shard").applyInArrow(build, SHARD_DDL)


def coded(points: np.ndarray, book: Codebook) -> bytes:
    """Codes of a shard's points, a slice at a time."""
    return b"".join(book.encode(points[a : a + 4096]).tobytes() for a in range(0, len(points), 4096))


def graph_code(graph: DataFrame, book: Codebook, kind: str = "float") -> DataFrame:
    """The same graphs with the nodes' codes in place of their points."""
    bounded_bytes(graph.sparkSession)
    shared = graph.sparkSession.sparkContext.broadcast(book)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                points = np.frombuffer(row.column("points")[0].as_py(), vectors.KINDS[kind]).reshape(row.column("n")[0].as_py(), -1)
                codes = pa.array([coded(points, shared.value)], pa.binary())
                yield pa.record_batch([*(row.column(f.name) for f in _SHARD if f.name != "points"), codes], schema=_SHARD)

    return graph.mapInArrow(run, SHARD_DDL)


def graph_nodes(graph: DataFrame) -> DataFrame:
    """shard, node, neighbours, is_entry: a row for each node."""
    bounded_bytes(graph.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.select(["shard", "n", "entry", "ids", "links"]).to_pylist():
                ids, links = np.frombuffer(r["ids"], "<i8"), np.frombuffer(r["links"], "<i4").reshape(r["n"], -1)
                lists = [ids[x[x >= 0]] for x in links]
                columns = [pa.array([r["shard"]] * r["n"], pa.int32()), pa.array(ids), pa.array(lists, pa.list_(pa.int64())), pa.array(np.arange(r["n"]) == r["entry"])]
                yield pa.record_batch(columns, names=["shard", "node", "neighbours", "is_entry"])

    return graph.mapInArrow(run, "shard int, node bigint, neighbours array<bigint>, is_entry boolean")


def graph_search(
    query_enc: DataFrame, graph: DataFrame, k: int, beam: int, centers: np.ndarray | None = None, probes: int = 1, shards: int = 1,
    book: Codebook | None = None, kind: str = "float",
) -> tuple[DataFrame, DataFrame]:
    """Top ``k`` nodes by a walk in every shard, and the number of distances computed: (query_id, rank, doc_id, score),
    (query_id, shard, n_dist). The beam is the only knob; it is at least ``k``. With ``book`` the shards hold codes.

    Given the ``centers`` and ``shards`` that a graph was built with, a query walks only the shards of its ``probes``
    centres of the largest product; a store partitioned by shard isn't read in the others.
    """
    return ranked(graph_walks(query_enc, graph, k, beam, centers, probes, shards, book, kind), k)


def ranked(walks: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """Lists and costs of ``graph_walks``."""
    flat = walks.select("query_id", F.explode("hits").alias("h")).select("query_id", "h.doc_id", "h.score")
    return topk(flat, k), walks.select("query_id", "shard", "n_dist")


def graph_walks(
    query_enc: DataFrame, graph: DataFrame, k: int, beam: int, centers: np.ndarray | None = None, probes: int = 1, shards: int = 1,
    book: Codebook | None = None, kind: str = "float",
) -> DataFrame:
    """The walks themselves, a row for each query and shard: query_id, shard, n_dist, hits."""
    spark = graph.sparkSession
    bounded_bytes(spark)
    ddl = WALKED.format("bigint" if kind == "fixed" else "double")
    out = None

    def walking(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, near, codes = shared.value
            for batch in batches:
                for r in (batch.slice(i, 1).to_pylist()[0] for i in range(batch.num_rows)):
                    ids, links = np.frombuffer(r["ids"], "<i8"), np.frombuffer(r["links"], "<i4").reshape(r["n"], -1)
                    if codes is None:
                        points = np.frombuffer(r["points"], vectors.KINDS[kind]).reshape(r["n"], -1)
                    else:
                        points = codes.unpacked(np.frombuffer(r["points"], np.uint8).reshape(r["n"], -1))
                    found = []
                    for at, (q, raw) in enumerate(own):
                        if near is not None and r["shard"] // shards not in near[at]:
                            continue
                        query = np.frombuffer(raw, vectors.KINDS[kind])
                        if codes is None:
                            far = lambda x, query=query: -(points[x] @ query)
                        else:
                            far = codes.distances(query, points)
                        seen, cost, n = walk(far, links, r["entry"], max(beam, k))
                        found.append((q, r["shard"], n, [{"doc_id": int(ids[i]), "score": -c} for i, c in zip(seen[:k].tolist(), cost[:k].tolist(), strict=True)]))
                    if found:
                        yield pa.RecordBatch.from_arrays(
                            [pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int32()), pa.array([f[2] for f in found], pa.int64()),
                             pa.array([f[3] for f in found], pa.list_(pa.struct([("doc_id", pa.int64()), ("score", pa.int64() if kind == "fixed" else pa.float64())])))],
                            names=["query_id", "shard", "n_dist", "hits"],
                        )

        return run

    for block in query_blocks(query_enc, "enc"):
        rows = [(r["bag_id"], bytes(r["enc"])) for r in block]
        near, own_shards = None, graph
        if centers is not None:
            product = np.stack([np.frombuffer(x, vectors.KINDS[kind]) for _, x in rows]) @ centers.T
            near = [set(x.tolist()) for x in np.argsort(-product, axis=1, kind="stable")[:, :probes]]
            wanted = sorted({c * shards + s for x in near for c in x for s in range(shards)})
            own_shards = graph.where(F.col("shard").isin(wanted))
        hits = own_shards.select("shard", "n", "entry", "ids", "links", "points").mapInArrow(walking(spark.sparkContext.broadcast((rows, near, book))), ddl)
        out = hits if out is None else out.union(hits)
    return out if out is not None else spark.createDataFrame([], ddl)
