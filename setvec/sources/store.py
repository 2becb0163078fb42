"""Written tables between steps, in the folder that all executors share, so that a lost executor costs a read."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
#: How often ``clear`` ran: what was kept before can't be read any more.
CLEARED = [0]
_BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a local session without one gets a temporary folder that goes with the process."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = tempfile.mkdtemp(prefix="setvec-core-")
        atexit.register(shutil.rmtree, _LOCAL[app], True)
    return f"file://{_LOCAL[app]}"


def own_folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/setvec-core/{spark.sparkContext.applicationId}"


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{own_folder(spark)}/{tag}-{uuid.uuid4().hex}"


def stored(df: DataFrame, tag: str, by: str | None = None) -> DataFrame:
    """Writes ``df`` and reads it back: the plan behind it is cut. ``by``: one folder for each value of a column."""
    path = new_path(df.sparkSession, tag)
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def clear(spark: SparkSession) -> None:
    """Removes all intermediate tables of this application."""
    CLEARED[0] += 1
    folder = spark._jvm.org.apache.hadoop.fs.Path(own_folder(spark))
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def bounded_bytes(spark: SparkSession, most: int = 64 << 20) -> None:
    """Arrow batches of at most about ``most`` bytes, for rows that hold a whole shard; a tighter setting stays."""
    now = spark.conf.get(_BATCH_BYTES)
    if not now.isdigit() or int(now) > most or int(now) <= 0:
        spark.conf.set(_BATCH_BYTES, str(most))
