"""What the operators share: written intermediate tables, Arrow batches cut to bounded slices, word spans over raw bytes.

Intermediate tables go to the folder of ``spark.checkpoint.dir`` as Parquet, so a lost executor costs a re-read and
never a recomputation of the whole lineage. Only a local session may lack that setting.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: dict[str, str] = {}

_BATCH = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")

#: Bytes of text that a kernel holds as arrays at once; one longer text is taken alone.
SLICE_BYTES = 2 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share. A local session without one gets a temporary folder; a cluster must name it."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = tempfile.mkdtemp(prefix="setvec-")
        atexit.register(shutil.rmtree, _LOCAL[app], True)
    return f"file://{_LOCAL[app]}"


def _own_folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/setvec/{spark.sparkContext.applicationId}"


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{_own_folder(spark)}/{tag}-{uuid.uuid4().hex}"


def clear(spark: SparkSession) -> None:
    """Removes all intermediate tables of this application. Results that still read them can't be read afterwards."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(_own_folder(spark))
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def free_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` doesn't have, in either case."""
    taken = {c.lower() for c in df.columns}
    while base in taken:
        base += "_"
    return base


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: the plan behind it is cut."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows, which the caller knows to be short; else ``df``, whose
    join then shuffles."""
    return F.broadcast(df) if df.count() <= rows else df


def bounded_batches(spark: SparkSession, records: int = 2048, size: int = 32 << 20) -> tuple[str, str]:
    """Keep Arrow batches small in rows and bytes, whatever the length of the texts, and return what was set before.

    Spark reads these settings when a plan runs, so they must hold for results that are returned unread; a caller's
    tighter settings stay. ``restored`` sets back what was returned."""
    before = tuple(spark.conf.get(name) for name in _BATCH)
    for name, old, most in zip(_BATCH, before, (records, size), strict=True):
        if _number(old) <= 0 or _number(old) > most:
            spark.conf.set(name, str(most))
    return before


def restored(spark: SparkSession, before: tuple[str, str]) -> None:
    for name, old in zip(_BATCH, before, strict=True):
        spark.conf.set(name, old)


def _number(setting: str) -> int:
    """A size setting in bytes; one with an unknown ending counts as no bound."""
    ends = {"b": 0, "k": 10, "kb": 10, "m": 20, "mb": 20, "g": 30, "gb": 30}
    digits = setting.lower().rstrip("bkmg")
    return int(digits) << ends.get(setting.lower()[len(digits) :], 0) if digits.lstrip("-").isdigit() else 0


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def arrow_map(
    df: DataFrame, kernel: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]], schema: str, most: int = SLICE_BYTES, column: str = "text"
) -> DataFrame:
    """``mapInArrow`` for a kernel that turns one bounded slice of rows into rows. Slices hold about ``most`` bytes of ``column``."""
    bounded_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, column, most):
                yield from kernel(part)

    return df.mapInArrow(run, schema)


def slices(batch: pa.RecordBatch, column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that each part holds at most ``most`` bytes of ``column``, or a single row."""
    if not batch.num_rows:
        return
    lengths = text_bytes(batch.column(column))[2]
    group = np.cumsum(lengths + 16) // most
    cuts = np.flatnonzero(np.diff(group)) + 1
    edges = [0, *cuts.tolist(), batch.num_rows]
    for a, b in zip(edges, edges[1:], strict=False):
        if b > a:
            yield batch.slice(a, b - a)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of a string or binary column as one buffer, with each row's start and length in it (null: length 0)."""
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1]
    at = at.astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and len(at) else np.zeros(0, np.uint8)
    lengths = np.diff(at)
    if column.null_count:
        lengths = np.where(column.is_null().to_numpy(zero_copy_only=False), 0, lengths)
    return raw, at[:-1] - at[0], lengths


def texts_of(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    """Python texts of a batch, null as the empty text."""
    return [x or "" for x in batch.column(column).to_pylist()]


def word_spans(raw: np.ndarray, starts: np.ndarray, lengths: np.ndarray, is_word: np.ndarray):
    """Starts, ends and document numbers of all words: runs of bytes marked in ``is_word`` that stay in one document.

    Where documents touch in the buffer a run is cut, so that a word never joins two documents.
    """
    n = len(raw)
    inside = np.zeros(n + 2, np.int8)
    inside[1:-1] = is_word[raw]
    step = np.diff(inside)
    begin, end = np.flatnonzero(step == 1), np.flatnonzero(step == -1)
    edges = starts[(starts > 0) & (starts < n)]
    edges = np.unique(edges[(inside[edges] == 1) & (inside[edges + 1] == 1)]) if len(edges) else edges
    if len(edges):
        begin, end = np.sort(np.concatenate([begin, edges])), np.sort(np.concatenate([end, edges]))
    filled = np.flatnonzero(lengths > 0)
    owner = filled[np.searchsorted(starts[filled], begin, side="right") - 1] if len(begin) else np.zeros(0, np.int64)
    return begin, end, owner


def held_fold(column: str, parts: int) -> F.Column:
    """crc32 of the id as text, modulo ``parts``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % parts


def rows_out(schema: pa.Schema, **columns) -> pa.RecordBatch:
    return pa.record_batch([pa.array(columns[f.name], f.type) for f in schema], schema=schema)
