"""Vector functions on array columns, and the packed form of a bag.

The column functions are higher-order functions of the engine: they keep small inputs and SQL readable. Bulk work runs
on packed bags: the vectors of a bag, row by row, as bytes of one number type.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Number types of packed vectors: whole fixed-point numbers, floats, and signs.
KINDS = {"fixed": "<i8", "float": "<f4", "sign": "<i1"}


def vec_dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def vec_dot_fixed(a: Column | str, b: Column | str) -> Column:
    """Of whole numbers, exactly."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("long") * y), F.lit(0).cast("long"), lambda s, x: s + x)


def vec_norm(a: Column | str) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column | str, b: Column | str) -> Column:
    return vec_dot(a, b) / (vec_norm(a) * vec_norm(b))


def vec_add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column | str, by: Column | float) -> Column:
    return F.transform(a, lambda x: x * by)


def vec_axpy(by: Column | float, a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda x, y: x * by + y)


def vec_normalize(a: Column | str) -> Column:
    """Unit length; a zero vector stays."""
    norm = vec_norm(a)
    return F.transform(a, lambda x: F.when(norm > 0, x / norm).otherwise(x.cast("double")))


def vec_argmax(a: Column | str) -> Column:
    """The first place (from 0) of the largest number."""
    return F.array_position(a, F.array_max(a)).cast("int") - 1


def vec_groups(a: Column | str, dim: int, size: int) -> Column:
    """Consecutive runs of ``size`` numbers."""
    return F.array(*[F.slice(a, 1 + i, size) for i in range(0, dim, size)])


def vec_fixed(a: Column | str, scale: int = 1 << 20) -> Column:
    """Fixed point: the nearest whole number, halves up."""
    return F.transform(a, lambda x: F.floor(x.cast("double") * scale + 0.5))


def vec_maxsim(query: Column | str, document: Column | str) -> Column:
    """MaxSim of two arrays of vectors: null for an empty document, 0 for an empty query."""
    doc = F.col(document) if isinstance(document, str) else document
    hit = F.transform(query, lambda q: F.array_max(F.transform(doc, lambda p: vec_dot(q, p))))
    total = F.aggregate(hit, F.lit(0.0), lambda s, x: s + x)
    return F.when(F.size(query) == 0, F.lit(0.0)).when(F.size(doc) == 0, F.lit(None).cast("double")).otherwise(total)


def valid_vector(a: Column | str, dim: int) -> Column:
    """Of length ``dim`` without nulls, NaN and infinities. Zero vectors pass."""
    fine = F.forall(a, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce((F.size(a) == dim) & fine, F.lit(False))


SQL_FUNCTIONS = {
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_norm": "(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "vec_add": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x + y)",
    "vec_maxsim": (
        "(q ARRAY<ARRAY<DOUBLE>>, p ARRAY<ARRAY<DOUBLE>>) RETURNS DOUBLE RETURN CASE WHEN size(q) = 0 THEN 0D ELSE aggregate(transform(q, "
        "x -> array_max(transform(p, y -> aggregate(zip_with(x, y, (a, b) -> a * b), 0D, (s, z) -> s + z)))), 0D, (s, z) -> s + z) END"
    ),
}


def unpack(column: pa.Array, dim: int, kind: str) -> tuple[np.ndarray, np.ndarray]:
    """All vectors of a packed column, stacked, and the bag number of each. A null bag is empty."""
    stored = np.dtype(KINDS[kind])
    raws = [x or b"" for x in column.to_pylist()]
    sizes = np.array([len(x) // (stored.itemsize * dim) for x in raws], np.int64)
    flat = np.frombuffer(b"".join(raws), stored).reshape(-1, dim)
    out = flat.astype(np.int64 if kind == "fixed" else np.float32)
    if kind == "sign":
        out /= np.float32(np.sqrt(dim))
    return out, np.repeat(np.arange(len(raws)), sizes)


def unpack_one(raw: bytes, dim: int, kind: str) -> np.ndarray:
    return unpack(pa.array([raw], pa.binary()), dim, kind)[0]
