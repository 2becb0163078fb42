"""Encoders of bags: packed, as one pass without a shuffle, and relational, as joins and sums that any engine can check.

The packed encoder is the one for large corpora: ``scan, project, MapInArrow``. The relational one makes a row for each
vector, repetition and dimension, and serves exact comparison, streams of single vectors, and mergeable partial sums.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setvec.functions import seeds, vectors
from setvec.operators import kernels
from setvec.plans.params import BUILT_IN, EncodeParams

ENCODED = "bag_id bigint, enc binary"


def kind_of(params: EncodeParams) -> str:
    return "fixed" if params.arithmetic == "fixed" else "float"


def _encoder(params: EncodeParams, side: str, kind: str, centers: np.ndarray | None):
    if params.partition not in BUILT_IN and params.partition not in kernels.PARTITIONS:
        raise ValueError(f"no partition named {params.partition!r}")
    own = kernels.PARTITIONS.get(params.partition)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if own is not None:
            kernels.register_partition(params.partition, own)
        for batch in batches:
            # A batch of encodings is cut so that it stays near 32 MB.
            step = max(1, (1 << 22) // params.width)
            for a in range(0, batch.num_rows, step):
                part = batch.slice(a, step)
                vecs, owner = vectors.unpack(part.column("vecs"), params.dim, kind)
                enc = kernels.encode(vecs, owner, part.num_rows, params, side, centers)
                raw = [row.astype(vectors.KINDS[kind_of(params)]).tobytes() for row in enc]
                yield pa.record_batch([part.column("bag_id"), pa.array(raw, pa.binary())], names=["bag_id", "enc"])

    return run


def encode_documents(bags: DataFrame, params: EncodeParams, centers: np.ndarray | None = None, kind: str | None = None) -> DataFrame:
    """bag_id, enc of packed bags (bag_id, vecs). An empty bag gets zeros."""
    return bags.select("bag_id", "vecs").mapInArrow(_encoder(params, "document", kind or kind_of(params), centers), ENCODED)


def encode_queries(bags: DataFrame, params: EncodeParams, centers: np.ndarray | None = None, kind: str | None = None) -> DataFrame:
    """As ``encode_documents``, with sums for blocks. Queries are never filled, whatever ``params.fill`` says."""
    return bags.select("bag_id", "vecs").mapInArrow(_encoder(params, "query", kind or kind_of(params), centers), ENCODED)


def to_arrays(encoded: DataFrame, params: EncodeParams) -> DataFrame:
    """Encodings as arrays of numbers."""
    number = "bigint" if params.arithmetic == "fixed" else "float"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [np.frombuffer(x, vectors.KINDS[kind_of(params)]) for x in batch.column("enc").to_pylist()]
            kind = pa.int64() if number == "bigint" else pa.float32()
            yield pa.record_batch([batch.column("bag_id"), pa.array(rows, pa.list_(kind))], names=["bag_id", "enc"])

    return encoded.mapInArrow(run, f"bag_id bigint, enc array<{number}>")


def to_sparse(encoded: DataFrame, params: EncodeParams) -> DataFrame:
    """The numbers that aren't 0: bag_id, idx, val."""
    arrays = to_arrays(encoded, params)
    hit = F.filter(F.transform("enc", lambda x, i: F.struct(i.alias("i"), x.alias("x"))), lambda s: s["x"] != 0)
    return arrays.select("bag_id", hit.alias("hit")).select("bag_id", F.col("hit.i").alias("idx"), F.col("hit.x").alias("val"))


# --- the relational encoder, over whole numbers -------------------------------------------------------------------


def long_tokens(tokens: DataFrame) -> DataFrame:
    """bag_id, pos, dim, x of fixed-point tokens (bag_id, pos, vec)."""
    return tokens.select("bag_id", "pos", F.posexplode("vec").alias("dim", "x"))


def planes_table(tokens: DataFrame, params: EncodeParams) -> DataFrame:
    """rep, bit, dim, g: a few thousand rows made from the seed."""
    planes = seeds.planes(params.seed, params.reps, params.hash_bits, params.dim, "int12")
    rows = [(r, b, d, int(g)) for (r, b, d), g in np.ndenumerate(planes)]
    return tokens.sparkSession.createDataFrame(rows, "rep int, bit int, dim int, g bigint")


def sign_cells(tokens: DataFrame, params: EncodeParams) -> DataFrame:
    """bag_id, pos, rep, cell of fixed-point tokens."""
    dots = long_tokens(tokens).join(F.broadcast(planes_table(tokens, params)), "dim")
    dots = dots.groupBy("bag_id", "pos", "rep", "bit").agg(F.sum(F.col("x") * F.col("g")).alias("dot"))
    bit = F.when(F.col("dot") > 0, F.expr("shiftleft(1, bit)")).otherwise(0)
    return dots.groupBy("bag_id", "pos", "rep").agg(F.sum(bit).cast("int").alias("cell"))


def block_sums(tokens: DataFrame, cells: DataFrame) -> DataFrame:
    """bag_id, rep, cell, dim, s, n: mergeable sums and counts, which partial aggregation adds before the shuffle."""
    rows = cells.join(tokens, ["bag_id", "pos"]).select("bag_id", "rep", "cell", F.posexplode("vec").alias("dim", "x"))
    return rows.groupBy("bag_id", "rep", "cell", "dim").agg(F.sum("x").alias("s"), F.count("*").alias("n"))


def filled_blocks(tokens: DataFrame, cells: DataFrame, params: EncodeParams) -> DataFrame:
    """bag_id, rep, cell, dim, v: means rounded down, and in empty cells the vector of the nearest code.

    An empty cell needs one vector of each occupied cell only, that of the smallest place, so fill joins occupied cells
    with cell numbers and never tokens with cells.
    """
    means = block_sums(tokens, cells).select("bag_id", "rep", "cell", "dim", F.floor(F.col("s") / F.col("n")).alias("v"))
    if not params.fill:
        return means
    occupied = cells.groupBy("bag_id", "rep", F.col("cell").alias("code")).agg(F.min("pos").alias("pos"))
    targets = occupied.select("*", F.explode(F.sequence(F.lit(0), F.lit(params.cells - 1))).alias("cell"))
    key = F.struct(F.expr("bit_count(code ^ cell)"), F.col("pos"))
    chosen = targets.groupBy("bag_id", "rep", "cell").agg(F.min_by("pos", key).alias("pos"), F.max((F.col("code") == F.col("cell")).cast("int")).alias("own"))
    holes = chosen.where("own = 0").join(tokens, ["bag_id", "pos"])
    filled = holes.select("bag_id", "rep", "cell", F.posexplode("vec").alias("dim", "v"))
    return means.union(filled.select("bag_id", "rep", "cell", "dim", "v"))


def projected_blocks(blocks: DataFrame, params: EncodeParams, value: str = "v") -> DataFrame:
    """bag_id, rep, cell, dim, v after the signs of each repetition; the map is linear, so it follows the sums."""
    if not params.projected:
        return blocks.select("bag_id", "rep", "cell", "dim", F.col(value).alias("v"))
    signs = seeds.inner_signs(params.seed, params.reps, params.proj_dim, params.dim, "int12")
    rows = [(r, j, d, int(s)) for (r, j, d), s in np.ndenumerate(signs)]
    table = blocks.sparkSession.createDataFrame(rows, "rep int, j int, dim int, sgn int")
    out = blocks.join(F.broadcast(table), ["rep", "dim"]).groupBy("bag_id", "rep", "cell", "j").agg(F.sum(F.col(value) * F.col("sgn")).alias("v"))
    return out.select("bag_id", "rep", "cell", F.col("j").alias("dim"), "v")


def final_numbers(blocks: DataFrame, params: EncodeParams) -> DataFrame:
    """bag_id, j, v after the last map, from projected blocks. For narrow widths; wide ones use the packed encoder, whose
    tiles are never stored."""
    span = params.cells * params.proj_dim
    rows = []
    for rep in range(params.reps):
        tile = seeds.final_signs(params.seed, rep, span, params.final_dim, "int12")
        rows += [(rep, i // params.proj_dim, i % params.proj_dim, j, int(s)) for (i, j), s in np.ndenumerate(tile)]
    table = blocks.sparkSession.createDataFrame(rows, "rep int, cell int, dim int, j int, sgn int")
    out = blocks.join(F.broadcast(table), ["rep", "cell", "dim"])
    return out.groupBy("bag_id", "j").agg(F.sum(F.col("v") * F.col("sgn")).alias("v"))
