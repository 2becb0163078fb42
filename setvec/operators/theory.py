"""Identities behind the encodings, as joins and as arrays: they check the encoders by another way."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setvec.functions.seeds import planes
from setvec.operators import kernels
from setvec.plans.params import EncodeParams


def oracle_concat(query: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two long vectors whose product is MaxSim, made with the best matching known."""
    return query.ravel(), doc[(query @ doc.T).argmax(1)].ravel()


def products(queries: DataFrame, docs: DataFrame) -> DataFrame:
    """query_id, qpos, doc_id, pos, dot of all pairs of fixed-point vectors: brute force by joins, for small inputs."""
    q = queries.select(F.col("bag_id").alias("query_id"), F.col("pos").alias("qpos"), F.posexplode("vec").alias("dim", "qx"))
    d = docs.select(F.col("bag_id").alias("doc_id"), "pos", F.posexplode("vec").alias("dim", "x"))
    return q.join(d, "dim").groupBy("query_id", "qpos", "doc_id", "pos").agg(F.sum(F.col("qx") * F.col("x")).alias("dot"))


def maxsim_by_joins(pairs: DataFrame) -> DataFrame:
    """query_id, doc_id, score of ``products``."""
    best = pairs.groupBy("query_id", "qpos", "doc_id").agg(F.max("dot").alias("best"))
    return best.groupBy("query_id", "doc_id").agg(F.sum("best").alias("score"))


def collisions(pairs: DataFrame, query_cells: DataFrame, doc_cells: DataFrame) -> DataFrame:
    """The rows of ``products`` whose vectors share a cell, by repetition."""
    q = query_cells.select(F.col("bag_id").alias("query_id"), F.col("pos").alias("qpos"), "rep", "cell")
    d = doc_cells.select(F.col("bag_id").alias("doc_id"), "pos", "rep", "cell")
    return pairs.join(q, ["query_id", "qpos"]).join(d, ["doc_id", "pos", "rep", "cell"])


def collision_score(pairs: DataFrame, query_cells: DataFrame, doc_cells: DataFrame) -> DataFrame:
    """query_id, doc_id, score: sums over query vectors of the mean product with the document vectors of their cell,
    over all repetitions. Without fill this is the product of the encodings."""
    same = collisions(pairs, query_cells, doc_cells)
    means = same.groupBy("query_id", "qpos", "doc_id", "rep").agg((F.sum("dot") / F.count("*")).alias("mean"))
    return means.groupBy("query_id", "doc_id").agg(F.sum("mean").alias("score"))


def collision_max(pairs: DataFrame, query_cells: DataFrame, doc_cells: DataFrame) -> DataFrame:
    """The same with the best product in place of the mean: what an ideal partition would give."""
    same = collisions(pairs, query_cells, doc_cells)
    tops = same.groupBy("query_id", "qpos", "doc_id", "rep").agg(F.max("dot").alias("best"))
    return tops.groupBy("query_id", "doc_id").agg(F.sum("best").alias("score"))


def same_bits(a: np.ndarray, b: np.ndarray, params: EncodeParams) -> float:
    """Share of repetitions in which two vectors fall in one cell."""
    codes = kernels.cells_of(np.stack([a, b]), params)
    return float((codes[0] == codes[1]).mean())


def agreeing_signs(a: np.ndarray, b: np.ndarray, params: EncodeParams) -> float:
    """Share of planes that two vectors lie on one side of; near 1 - angle / pi."""
    flat = planes(params.seed, params.reps, params.hash_bits, params.dim, params.plane_law).reshape(-1, params.dim)
    return float(((flat @ a > 0) == (flat @ b > 0)).mean())
