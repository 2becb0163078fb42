"""A session with the settings that the engine is meant to run with; a session that is given works as it is."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Re-planning at run time deals skewed joins and small partitions; Arrow batches stay bounded in bytes for packed rows.
SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.adaptive.coalescePartitions.enabled": "true",
    "spark.sql.execution.arrow.maxRecordsPerBatch": "4096",
    "spark.sql.execution.arrow.maxBytesPerBatch": str(64 << 20),
    "spark.sql.session.timeZone": "UTC",
}


def session(name: str = "setvec", master: str | None = None, partitions: int | None = None, **more: str) -> SparkSession:
    """``partitions``: of a shuffle; about two for each core, or the shuffled bytes over 128 MB, whichever is more."""
    builder = SparkSession.builder.appName(name)
    if master:
        builder = builder.master(master)
    for key, value in {**SETTINGS, **({"spark.sql.shuffle.partitions": str(partitions)} if partitions else {}), **more}.items():
        builder = builder.config(key, value)
    return builder.getOrCreate()
