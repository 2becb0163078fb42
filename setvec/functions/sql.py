"""The SQL surface: views of the given tables, vector functions the optimizer sees through, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from setvec.functions import text, vectors
from setvec.operators import kernels
from setvec.plans.params import EncodeParams
from setvec.sources import planes, tables


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in tables.SCHEMAS:
        tables.load(spark, sf_dir, name).createOrReplaceTempView(name)


def register_functions(spark: SparkSession) -> None:
    for name, body in vectors.SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")


def encode_bag_agg(params: EncodeParams):
    """A grouped aggregate for SQL: the document encoding of a group's vectors."""

    @F.pandas_udf("array<float>")
    def encode_bag(vecs: pd.Series) -> np.ndarray:
        stacked = np.stack([np.asarray(v, np.float32) for v in vecs])
        return kernels.encode(stacked, np.zeros(len(stacked), np.int64), 1, params, "document")[0].tolist()

    return encode_bag


def maxsim_packed(dim: int, kind: str = "float"):
    """A scalar function on packed bags: MaxSim of two binary columns; null for an empty document."""

    @F.pandas_udf("double")
    def score(query: pd.Series, doc: pd.Series) -> pd.Series:
        out = []
        for a, b in zip(query, doc, strict=True):
            q, d = vectors.unpack_one(a or b"", dim, kind), vectors.unpack_one(b or b"", dim, kind)
            out.append(0.0 if not len(q) else None if not len(d) else float(kernels.maxsim(q, d, np.array([0]))[0]))
        return pd.Series(out, dtype="float64")

    return score


def explode_cells(params: EncodeParams):
    """A table function: the cell of one vector in each repetition."""

    @F.udtf(returnType="rep int, cell int")
    class ExplodeCells:
        def eval(self, vec: list) -> Iterator[tuple[int, int]]:
            codes = kernels.cells_of(np.array([vec], np.float32), params)[0]
            yield from ((r, int(c)) for r, c in enumerate(codes))

    return ExplodeCells


@F.udtf(returnType="chunk_no int, words array<string>")
class ChunkText:
    """A table function: windows of words of one text."""

    def eval(self, body: str, size: int, stride: int) -> Iterator[tuple[int, list[str]]]:
        import re

        found = re.findall(r"[^\W_]+", (body or "").lower())
        for n, a in enumerate(range(0, max(1, len(found) - size + stride), stride) if found else ()):
            yield n, list(dict.fromkeys(found[a : a + size]))


@F.udtf(returnType="query_id bigint, rank int, doc_id bigint, score bigint")
class TopkSearch:
    """A table function over partitions of a table (query_id, doc_id, score): the ``k`` best of each partition."""

    def __init__(self) -> None:
        self.held: list[tuple[int, int, int]] = []

    def eval(self, row, k: int) -> None:
        import heapq

        item = (row["score"], -row["doc_id"], row["query_id"])
        (heapq.heappush if len(self.held) < k else heapq.heappushpop)(self.held, item)

    def terminate(self) -> Iterator[tuple[int, int, int, int]]:
        for rank, (score, doc, query) in enumerate(sorted(self.held, reverse=True), 1):
            yield query, rank, -doc, score


def register_all(spark: SparkSession, sf_dir: str | None = None, params: EncodeParams | None = None) -> None:
    """Everything under its SQL name: vec_dot, vec_norm, vec_add, vec_maxsim, chunk_text, the parameter source, and with
    ``params`` explode_cells, encode_bag_agg and maxsim_packed."""
    register_functions(spark)
    planes.register(spark)
    spark.udtf.register("chunk_text", ChunkText)
    spark.udtf.register("topk_search", TopkSearch)
    if params is not None:
        spark.udtf.register("explode_cells", explode_cells(params))
        spark.udf.register("encode_bag_agg", encode_bag_agg(params))
        spark.udf.register("maxsim_packed", maxsim_packed(params.dim))
    if sf_dir is not None:
        register_views(spark, sf_dir)


WORDS = text.words
