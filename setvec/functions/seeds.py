"""Random planes, signs and noise as functions of (purpose, seed, position) alone.

Nothing hangs on a partition or a task, so a retried task, another cluster and a stream give the same encoding. The
``int12`` law takes twelve bytes of an md5 sum, so that SQL engines can draw the same numbers; the ``gaussian`` law takes
a counter-based generator keyed by purpose, seed and repetition.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

PURPOSES = ("plane", "inner", "final", "center", "pqinit", "noise", "shard")


def digest(purpose: str, seed: int, *at: int | str) -> bytes:
    return hashlib.md5(":".join(map(str, (purpose, seed, *at))).encode()).digest()


def int12(purpose: str, seed: int, *at: int | str) -> int:
    """About Gaussian: twice the sum of twelve bytes less the mean (standard deviation about 512)."""
    return 2 * sum(digest(purpose, seed, *at)[:12]) - 3060


def sign(purpose: str, seed: int, *at: int | str) -> int:
    """-1 or 1, by the last bit of the first byte."""
    return 2 * (digest(purpose, seed, *at)[0] & 1) - 1


def generator(purpose: str, seed: int, rep: int = 0) -> np.random.Generator:
    key = int.from_bytes(digest(purpose, seed, rep)[:16], "little")
    return np.random.Generator(np.random.Philox(key=key))


@lru_cache(maxsize=64)
def planes(seed: int, reps: int, bits: int, dim: int, law: str) -> np.ndarray:
    """Directions (reps, bits, dim) whose signs make the cells."""
    if law == "int12":
        out = [[[int12("plane", seed, r, b, d) for d in range(dim)] for b in range(bits)] for r in range(reps)]
        return np.array(out, np.int64).reshape(reps, bits, dim)
    return np.stack([generator("plane", seed, r).standard_normal((bits, dim)) for r in range(reps)]).astype(np.float32)


@lru_cache(maxsize=64)
def inner_signs(seed: int, reps: int, proj: int, dim: int, law: str) -> np.ndarray:
    """Signs (reps, proj, dim) of the maps inside blocks, fresh for each repetition."""
    if law == "int12":
        out = [[[sign("inner", seed, r, j, d) for d in range(dim)] for j in range(proj)] for r in range(reps)]
        return np.array(out, np.int64)
    draws = [generator("inner", seed, r).integers(0, 2, (proj, dim), dtype=np.int8) for r in range(reps)]
    return (2 * np.stack(draws) - 1).astype(np.float32)


def final_signs(seed: int, rep: int, rows: int, final: int, law: str) -> np.ndarray:
    """The tile (rows, final) of the last map that belongs to one repetition, made anew wherever it is needed."""
    if law == "int12":
        return np.array([[sign("final", seed, rep * rows + i, j) for j in range(final)] for i in range(rows)], np.int64)
    return (2 * generator("final", seed, rep).integers(0, 2, (rows, final), dtype=np.int8) - 1).astype(np.float32)


def int12_column(key: Column) -> Column:
    """``int12`` of a text column that holds purpose, seed and position joined by colons."""
    m = F.md5(key)
    byte = [F.conv(F.substring(m, 1 + 2 * i, 2), 16, 10).cast("long") for i in range(12)]
    total = byte[0]
    for b in byte[1:]:
        total = total + b
    return total * 2 - 3060


def int12_sql(key: str) -> str:
    """The same in DuckDB's SQL."""
    return "(2 * (" + " + ".join(f"('0x' || substr(md5({key}), {1 + 2 * i}, 2))::BIGINT" for i in range(12)) + ") - 3060)"


def sign_sql(key: str) -> str:
    return f"(2 * (('0x' || substr(md5({key}), 1, 2))::BIGINT & 1) - 1)"
