"""N-gram Jaccard join with Bayesian pruning of candidates.

Texts with one set of five-word shingles form a class; the smallest id stands for it. Representatives whose MinHash
values agree on a whole band are joined into neighbourhoods, by labels that spread over the bands' stars. Within a
neighbourhood pairs are compared block by block, never listed: after each round of MinHash values a pair is dropped when
the posterior probability (uniform prior) that its Jaccard similarity reaches the threshold is below ``TOLERANCE``; the
rest are verified on their whole shingle sets. Blocks of a large neighbourhood are dealt to many tasks. A block gives
link counts and one spanning forest, so no group of copies or near copies is expanded into its pairs.

Result: a row per document with class_id (smallest id of all documents that links connect), n_links (other documents of
similarity >= 0.8, copies counted), set_id (smallest id with the same shingle set), n_copies (documents of that set) and
n_set_links (linked sets). Null and empty texts have equal, empty sets and are copies of each other. A null id has null
classes and no links. Repeated rows count as copies; one id with several texts is taken by text. An empty table gives no
rows; other columns are ignored (``kept`` keeps them).
"""

from __future__ import annotations

from collections.abc import Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, bounded_batches, documents, free_name, rows_out, slices, small, stored
from setvec.llm.shingles import mixed, shingle_sets

BANDS, ROWS = 32, 5
HASHES = BANDS * ROWS
ROUNDS = (16, 32, 64, 96, 128, 160)
#: Similarity is at least NUMERATOR / DENOMINATOR, compared in whole numbers.
NUMERATOR, DENOMINATOR = 4, 5
TOLERANCE = 1e-6
CHUNK = 256
#: Shingles of a chunk, whatever the number of its rows; a single longer text is a chunk of its own.
WEIGHT = 1 << 20
#: Rows that are broadcast at most, each of ids and counts only.
MEMBERS = 200_000

_RNG = np.random.default_rng(11)
_A = _RNG.integers(0, 1 << 31, HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_B = _RNG.integers(0, 1 << 31, HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)

_SIGNED = pa.schema([("doc_id", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("n", pa.int64()), ("bands", pa.list_(pa.int64()))])
SIGNED_DDL = "doc_id bigint, k1 bigint, k2 bigint, n bigint, bands array<bigint>"
_LINKS = pa.schema([(n, pa.int64()) for n in ("rep", "peer", "links", "set_links")])
LINKS_DDL = "rep bigint, peer bigint, links bigint, set_links bigint"


def least_matches(n: int, tolerance: float = TOLERANCE) -> int:
    """The fewest agreeing values of ``n`` with a posterior of at least ``tolerance`` for reaching the threshold.

    With a uniform prior that posterior is the chance of at most m successes in n + 1 trials at the threshold.
    """
    t = NUMERATOR / DENOMINATOR
    total = 0.0
    for m in range(n + 1):
        total += comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
        if total >= tolerance:
            return m
    return n


_LEAST = {n: least_matches(n) for n in ROUNDS}


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """MinHash values, a row per set that isn't empty."""
    flat = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
    out = np.zeros((len(sets), HASHES), np.uint32)
    if not len(flat):
        return out
    starts = np.cumsum([0, *map(len, sets[:-1])])
    low, high = flat.astype(np.uint32), (flat >> np.uint64(32)).astype(np.uint32)
    one, two = np.empty_like(low), np.empty_like(low)
    for i in range(HASHES):
        np.multiply(low, _A[i], out=one)
        np.multiply(high, _B[i], out=two)
        np.bitwise_xor(one, two, out=one)
        out[:, i] = np.minimum.reduceat(one, starts)
    return out


def set_key(items: np.ndarray) -> tuple[int, int]:
    """128 bits of a set that don't depend on order."""
    one, two = mixed(items).sum(dtype=np.uint64), mixed(items ^ np.uint64(0xD6E8FEB86659FD93)).sum(dtype=np.uint64)
    return int(one.astype(np.int64)), int(two.astype(np.int64))


def _sign(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    sets = list(shingle_sets(batch.column("text")))
    filled = [i for i, s in enumerate(sets) if len(s)]
    marks = signatures([sets[i] for i in filled]).reshape(len(filled), BANDS, ROWS).astype(np.uint64)
    bands = np.full((len(filled), BANDS), np.uint64(17))
    for k in range(ROWS):
        bands = mixed(bands * np.uint64(31) + marks[:, :, k])
    listed: list = [[]] * len(sets)
    for i, row in zip(filled, bands.astype(np.int64), strict=True):
        listed[i] = row
    keys = [set_key(s) for s in sets]
    yield rows_out(_SIGNED, doc_id=batch.column("doc_id"), k1=[k[0] for k in keys], k2=[k[1] for k in keys], n=list(map(len, sets)), bands=listed)


def signed(docs: DataFrame) -> DataFrame:
    """Each document's set key, set size and band hashes."""
    return arrow_map(docs.select(F.col("doc_id").cast("long"), "text"), _sign, SIGNED_DDL)


def components(edges: DataFrame) -> DataFrame:
    """id, label: the smallest id of each connected component of edges (a, b). Labels spread by the smallest label of
    the neighbours and then of the label's own label, until none changes; each round is a written table."""
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    both = stored(both.where("a != b").distinct(), "edges")
    labels = stored(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("a"), F.min("b")).alias("label")), "labels")
    while True:
        near = both.join(labels.select(F.col("id").alias("b"), "label"), "b").groupBy(F.col("a").alias("id")).agg(F.min("label").alias("near"))
        step = labels.join(near, "id").select("id", F.col("label").alias("was"), F.least("label", "near").alias("label"))
        step = stored(step, "labels")
        top = step.select(F.col("id").alias("label"), F.col("label").alias("top"))
        new = stored(step.join(top, "label").select("id", "was", F.col("top").alias("label")), "labels")
        settled = new.where("label != was").isEmpty()
        labels = new.select("id", "label")
        if settled:
            return labels


def neighbourhoods(reps: DataFrame) -> DataFrame:
    """Labels of representatives (rep, bands) that share a band with another, over the stars of all bands."""
    rows = reps.select("rep", F.posexplode("bands").alias("band", "value"))
    least = rows.groupBy("band", "value").agg(F.min("rep").alias("low"), F.count("*").alias("n")).where("n > 1").drop("n")
    stars = rows.join(least, ["band", "value"]).where("rep != low").select(F.col("rep").alias("a"), F.col("low").alias("b"))
    return components(stars)


def _verified(i: np.ndarray, j: np.ndarray, sets: list[np.ndarray], sizes: np.ndarray) -> np.ndarray:
    """Which pairs reach the threshold, by counts of common shingles over the documents that occur in pairs."""
    used, where = np.unique(np.concatenate([i, j]), return_inverse=True)
    a, b = where[: len(i)], where[len(i) :]
    owner = np.repeat(np.arange(len(used)), sizes[used])
    _, item, count = np.unique(np.concatenate([sets[u] for u in used]), return_inverse=True, return_counts=True)
    shared = count > 1
    keep = shared[item]
    item, owner = (np.cumsum(shared) - 1)[item[keep]], owner[keep]
    order = np.argsort(item, kind="stable")
    item, owner = item[order], owner[order]
    common = np.zeros((len(used), len(used)), np.float32)
    width = 8192
    for low in range(0, int(shared.sum()), width):
        lo, hi = np.searchsorted(item, [low, low + width])
        block = np.zeros((len(used), width), np.float32)
        block[owner[lo:hi], item[lo:hi] - low] = 1
        common += block @ block.T
    both = common[a, b].astype(np.int64)
    return both * DENOMINATOR >= NUMERATOR * (sizes[i] + sizes[j] - both)


def linked(sets: list[np.ndarray], marks: np.ndarray, side: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of rows whose similarity reaches the threshold; with ``side`` only pairs from different sides."""
    sizes = np.array(list(map(len, sets)), np.int64)
    rows = np.flatnonzero(~side) if side is not None else np.arange(len(sets))
    cols = np.flatnonzero(side) if side is not None else rows
    small, large = np.minimum(sizes[rows][:, None], sizes[cols]), np.maximum(sizes[rows][:, None], sizes[cols])
    open_pairs = small * DENOMINATOR >= large * NUMERATOR
    if side is None:
        open_pairs &= np.arange(len(rows))[:, None] < np.arange(len(cols))
    agree = np.zeros(open_pairs.shape, np.uint16)
    for h in range(ROUNDS[0]):
        agree += marks[rows, h][:, None] == marks[cols, h]
    x, y = np.nonzero(open_pairs & (agree >= _LEAST[ROUNDS[0]]))
    agree, i, j = agree[x, y].astype(np.int64), rows[x], cols[y]
    for before, n in zip(ROUNDS, ROUNDS[1:], strict=False):
        agree += (marks[i, before:n] == marks[j, before:n]).sum(1)
        stay = agree >= _LEAST[n]
        i, j, agree = i[stay], j[stay], agree[stay]
    if not len(i):
        return i, j
    true = _verified(i, j, sets, sizes)
    return i[true], j[true]


def _forest(i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for a, b in zip(i.tolist(), j.tolist(), strict=True):
        if (p := root(a)) != (q := root(b)):
            parent[max(p, q)] = min(p, q)
            out.append((a, b))
    return out


def _compare(table: pa.Table) -> pa.Table:
    """Links within one group of rows (comp, rep, k1, k2, copies, chunk, first, second, text), neighbourhood by neighbourhood."""
    ids: list[tuple] = []
    sets: list[np.ndarray] = []
    meta = zip(*(table.column(c).to_pylist() for c in ("comp", "rep", "k1", "k2", "copies", "chunk", "first", "second")), strict=True)
    whole = table.select(["text"]).combine_chunks().to_batches()
    items = (s for b in whole for part in slices(b) for s in shingle_sets(part.column("text")))
    seen = set()
    for row, s in zip(meta, items, strict=True):
        if row[:2] not in seen and len(s) and set_key(s) == row[2:4]:
            seen.add(row[:2])
            ids.append(row)
            sets.append(s)
    marks = np.concatenate([signatures(sets[a : a + 64]) for a in range(0, len(sets), 64)]) if sets else None
    by_comp: dict[int, list[int]] = {}
    for n, row in enumerate(ids):
        by_comp.setdefault(row[0], []).append(n)
    out: list[tuple] = []
    for members in by_comp.values():
        members.sort(key=lambda n: ids[n][1])
        chunk, (first, second) = np.array([ids[n][5] for n in members]), ids[members[0]][6:]
        across = first != second
        if len(members) < 2 or (across and len(set(chunk.tolist())) < 2):
            continue
        i, j = linked([sets[n] for n in members], marks[members], chunk == second if across else None)
        copies = np.array([ids[n][4] for n in members], np.int64)
        rep = [ids[n][1] for n in members]
        links = np.bincount(i, copies[j], len(members)) + np.bincount(j, copies[i], len(members))
        count = np.bincount(i, minlength=len(members)) + np.bincount(j, minlength=len(members))
        out += [(rep[n], None, int(links[n]), int(count[n])) for n in np.flatnonzero(count).tolist()]
        out += [(rep[a], rep[b], 0, 0) for a, b in _forest(i, j)]
    columns = list(zip(*out, strict=True)) or [[]] * len(_LINKS)
    return pa.table([pa.array(c, f.type) for c, f in zip(columns, _LINKS, strict=True)], schema=_LINKS)


def set_links(docs: DataFrame, reps: DataFrame, labels: DataFrame, chunk: int = CHUNK, weight: int = WEIGHT) -> DataFrame:
    """Link counts and forests of all neighbourhoods. Small ones share a group; one over ``chunk`` rows or ``weight``
    shingles is cut into chunks, and each pair of chunks is a group, so a group holds at most about two chunks of whole
    texts, however long they are."""
    bounded_batches(docs.sparkSession)
    known = labels.join(reps.select(F.col("rep").alias("id"), "k1", "k2", "copies", "n"), "id")
    known = stored(known, "known")
    sizes = known.groupBy("label").agg(F.count("*").alias("size"), F.sum("n").alias("mass"))
    parts = F.greatest(F.ceil(F.col("size") / chunk), F.ceil(F.col("mass") / weight)).cast("int")
    sizes = sizes.select("label", "size", "mass", parts.alias("parts"))
    whole = F.when(F.col("parts") == 1, F.col("size")), F.when(F.col("parts") == 1, F.col("mass"))
    totals = sizes.agg(F.sum(whole[0]).alias("n"), F.sum(whole[1]).alias("mass")).first()
    bins = max(1, -(-(totals["n"] or 0) // chunk), -(-(totals["mass"] or 0) // weight))
    rows = known.drop("n").join(sizes.select("label", "parts"), "label")
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64("id"), "parts").cast("int"))
    others = F.when(F.col("parts") > 1, F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array(F.lit(-1)))
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    # Rows of a few numbers: when they are few, only their texts are shuffled; else all texts are.
    rows = texts.join(small(stored(rows.withColumn("others", others), "members"), MEMBERS), "id")
    rows = rows.withColumn("other", F.explode("others"))
    low, high = F.least("chunk", "other"), F.greatest("chunk", "other")
    alone = F.col("parts") == 1
    rows = rows.select(
        F.when(alone, F.pmod(F.xxhash64("label"), F.lit(bins))).otherwise(F.xxhash64("label", low, high)).alias("key"),
        F.when(alone, F.lit(-1)).otherwise(low).alias("first"), F.when(alone, F.lit(-1)).otherwise(high).alias("second"),
        F.col("label").alias("comp"), F.col("id").alias("rep"), "k1", "k2", "copies", "chunk", "text",
    )
    return rows.groupBy("key", "first", "second").applyInArrow(_compare, LINKS_DDL)


def near_classes(docs: DataFrame, chunk: int = CHUNK, weight: int = WEIGHT) -> DataFrame:
    """doc_id, class_id, n_links, set_id, n_copies, n_set_links, a row for each row of ``docs``."""
    rows = stored(signed(docs), "signed")
    keyed = rows.where(F.col("doc_id").isNotNull())
    reps = stored(keyed.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), F.max("n").alias("n")), "reps")
    banded = keyed.where("n > 0").join(reps.withColumnRenamed("rep", "doc_id").drop("copies", "n"), ["doc_id", "k1", "k2"], "left_semi")
    labels = neighbourhoods(banded.select(F.col("doc_id").alias("rep"), "bands").dropDuplicates(["rep", "bands"]))
    links = stored(set_links(docs, reps, labels, chunk, weight), "links")
    classes = components(links.where("peer is not null").select(F.col("rep").alias("a"), F.col("peer").alias("b")))
    counts = links.groupBy("rep").agg(F.sum("links").alias("links"), F.sum("set_links").alias("set_links"))
    info = reps.join(counts, "rep", "left").join(classes.withColumnsRenamed({"id": "rep", "label": "class_id"}), "rep", "left")
    info = info.select(
        "k1", "k2", F.col("rep").alias("set_id"), F.coalesce("class_id", "rep").alias("class_id"), F.col("copies").alias("n_copies"),
        F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("set_links", F.lit(0)).alias("n_set_links"),
    )
    known = keyed.select("doc_id", "k1", "k2").join(info, ["k1", "k2"])
    known = known.select("doc_id", "class_id", (F.col("links") + F.col("n_copies") - 1).alias("n_links"), "set_id", "n_copies", "n_set_links")
    no_id = rows.where(F.col("doc_id").isNull()).select("doc_id")
    nothing, zero = F.lit(None).cast("long"), F.lit(0).cast("long")
    no_id = no_id.select("doc_id", nothing.alias("class_id"), zero.alias("n_links"), nothing.alias("set_id"), zero.alias("n_copies"), zero.alias("n_set_links"))
    return known.union(no_id)


def kept(docs: DataFrame) -> DataFrame:
    """One document of each class, that of the smallest id, with all columns. Rows without an id stay; rows that repeat
    the smallest id stay together."""
    name = free_name(docs, "gone")
    gone = stored(near_classes(docs).where("doc_id != class_id").select(F.col("doc_id").alias(name)).distinct(), "gone")
    return docs.join(small(gone, MEMBERS), F.col("doc_id").cast("long") == F.col(name), "left_anti")


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_classes(documents(spark, sf_dir))
