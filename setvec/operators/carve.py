"""Merging close query vectors before re-scoring.

Groups are greedy: in order of place, a vector that no earlier seed takes is a seed, and takes all later vectors whose
product with it reaches the threshold. A group is replaced by its sum, which isn't normalised. The column form says the
same without a loop over the data: a vector is a seed iff no earlier seed reaches it, others join their first such seed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setvec.functions import seeds, vectors
from setvec.operators import kernels


def carve_bags(bags: DataFrame, tau: float, dim: int, kind: str = "float") -> DataFrame:
    """bag_id, n (groups), n_before, vecs (their sums) of packed query bags."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for raw in batch.column("vecs").to_pylist():
                query = vectors.unpack_one(raw or b"", dim, kind)
                sums, _ = kernels.carve(query, tau)
                out.append((len(sums), len(query), sums.astype(vectors.KINDS["fixed" if kind == "fixed" else "float"]).tobytes()))
            n, before, vecs = zip(*out, strict=True) if out else ((), (), ())
            columns = [batch.column("bag_id"), pa.array(n, pa.int32()), pa.array(before, pa.int32()), pa.array(vecs, pa.binary())]
            yield pa.record_batch(columns, names=["bag_id", "n", "n_before", "vecs"])

    return bags.select("bag_id", "vecs").mapInArrow(run, "bag_id bigint, n int, n_before int, vecs binary")


def seed_places(items: str, tau: float) -> Column:
    """Places of the seeds in an array column of vectors, by array functions alone."""
    dot = f"aggregate(zip_with({items}[j], {items}[i], (x, y) -> cast(x as double) * y), 0D, (s, x) -> s + x)"
    step = f"if(exists(acc, j -> {dot} >= {tau}D), acc, array_append(acc, i))"
    return F.expr(f"aggregate(sequence(0, size({items}) - 1), cast(array() as array<int>), (acc, i) -> {step})")


def group_seeds(items: str, seeds_column: str, tau: float) -> Column:
    """Each vector's seed: the first that reaches it; a seed is its own."""
    dot = f"aggregate(zip_with({items}[j], {items}[i], (x, y) -> cast(x as double) * y), 0D, (s, x) -> s + x)"
    return F.expr(f"transform(sequence(0, size({items}) - 1), i -> filter({seeds_column}, j -> j = i or (j < i and {dot} >= {tau}D))[0])")


def kmeans_bags(bags: DataFrame, k: int, dim: int, rounds: int = 10, seed: int = 42) -> DataFrame:
    """The rejected alternative: a fixed number of groups for each query, by k-means on its vectors; sums again."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, vecs = [], []
            for raw in batch.column("vecs").to_pylist():
                query = vectors.unpack_one(raw or b"", dim, "float")
                distinct = np.unique(query, axis=0)
                start = distinct[np.sort(seeds.generator("center", seed).permutation(len(distinct))[:k])]
                code = kernels.nearest_center(query, kernels.lloyd(query, start, rounds)) if len(query) else np.zeros(0, np.int64)
                sums = np.stack([query[code == c].sum(0) for c in np.unique(code)]) if len(query) else query
                n.append(len(sums))
                vecs.append(sums.astype("<f4").tobytes())
            yield pa.record_batch([batch.column("bag_id"), pa.array(n, pa.int32()), pa.array(vecs, pa.binary())], names=["bag_id", "n", "vecs"])

    return bags.select("bag_id", "vecs").mapInArrow(run, "bag_id bigint, n int, vecs binary")
