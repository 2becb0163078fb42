"""Streams of items: the encoders need no statistics of the data, so what arrives later is encoded by the same maps.

Whole bags are encoded statelessly. Single vectors are added to mergeable blocks by event-time window; a state per
document keeps its vectors where blocks must also be filled or vectors removed.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from setvec.functions import vectors
from setvec.operators import kernels
from setvec.operators.encode import ENCODED, encode_documents, kind_of, to_arrays
from setvec.plans.params import EncodeParams
from setvec.sources import store, tables


def read_dir(spark: SparkSession, path: str, schema: str, form: str = "parquet", files: int = 100) -> DataFrame:
    """A stream of files as they appear in a folder."""
    return spark.readStream.schema(schema).format(form).option("maxFilesPerTrigger", files).load(path)


def rate_tokens(spark: SparkSession, rows: int, dim: int, per_bag: int = 4) -> DataFrame:
    """A stream of made-up vectors for trials, ``rows`` each batch: bag_id, pos, vec, by the engine's own rate source."""
    made = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).load()
    turn = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.cos(F.col("value") * (i + 1)).cast("float"))
    return made.select(F.expr(f"value div {per_bag}").alias("bag_id"), F.expr(f"cast(value % {per_bag} as int)").alias("pos"), turn.alias("vec"))


def encode_stream(bags: DataFrame, params: EncodeParams, centers: np.ndarray | None = None) -> DataFrame:
    """Packed bags of a stream to encodings, batch by batch without state."""
    return encode_documents(bags, params, centers)


def window_bags(events: DataFrame, length: str, delay: str, slide: str | None = None, by: str = "user_id") -> DataFrame:
    """Events of one user and window: count and the sum of a hash of their types. Rows later than ``delay`` are dropped.

    (sum, count) pairs add up, so windows are aggregated in parts before the shuffle."""
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    value = F.conv(F.substring(F.md5("event_type"), 1, 2), 16, 10).cast("long")
    return events.withWatermark("ts", delay).groupBy(by, span).agg(F.count("*").alias("n"), F.sum(value).alias("s"))


def session_counts(events: DataFrame, gap: str, delay: str, by: str = "user_id") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(by, F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def views_to_purchases(events: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """Stream to stream: a purchase within the interval after a view of the same user."""
    views = events.where("event_type = 'view'").select(F.col("user_id").alias("v_user"), F.col("event_id").alias("view_id"), F.col("ts").alias("v_ts")).withWatermark("v_ts", delay)
    buys = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("p_ts")).withWatermark("p_ts", delay)
    return views.join(buys, F.expr(f"v_user = user_id and p_ts > v_ts and p_ts <= v_ts + interval {within}")).select("user_id", "view_id", "purchase_id")


def without_repeats(events: DataFrame, delay: str) -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def vector_updates(updates: DataFrame, params: EncodeParams) -> DataFrame:
    """A document's encoding after each batch of changes (doc_id, pos, vec, gone): the state is the bag itself, since
    fill needs vectors. A repeated place replaces its vector; ``gone`` removes it."""

    def apply(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = dict(zip(state.get[0], state.get[1], strict=True)) if state.exists else {}
        for rows in batches:
            for pos, vec, gone in zip(rows["pos"], rows["vec"], rows["gone"], strict=True):
                if gone:
                    held.pop(int(pos), None)
                else:
                    held[int(pos)] = np.asarray(vec, vectors.KINDS[kind_of(params)]).tobytes()
        places = sorted(held)
        state.update((places, [held[p] for p in places]))
        raw = b"".join(held[p] for p in places)
        vecs = vectors.unpack_one(raw, params.dim, kind_of(params))
        enc = kernels.encode(vecs, np.zeros(len(vecs), np.int64), 1, params, "document")[0]
        yield pd.DataFrame({"bag_id": [key[0]], "n": [len(places)], "enc": [enc.astype(vectors.KINDS[kind_of(params)]).tobytes()]})

    return updates.groupBy("doc_id").applyInPandasWithState(
        apply, "bag_id bigint, n int, enc binary", "places array<int>, vecs array<binary>", "update", GroupStateTimeout.NoTimeout
    )


def search_stream(queries: DataFrame, run: Callable[[DataFrame], DataFrame], path: str, checkpoint: str):
    """Stream of query bags against a static index: each batch is searched and its lists are written to a folder of its
    own, so that a batch that runs again after a failure replaces what it wrote."""

    def batch(rows: DataFrame, number: int) -> None:
        run(rows).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return queries.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_recall(lists: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """batch, queries, recall, running: recall at ``k`` of each batch that ``search_stream`` wrote, and of all batches so
    far. One row a batch is ordered, whatever the number of queries."""
    first = lists.groupBy("batch", "query_id", "doc_id").agg(F.min("rank").alias("rank"))
    asked = lists.select("batch", "query_id").distinct()
    hits = asked.join(truth, "query_id").join(first, ["batch", "query_id", "doc_id"], "left")
    per = hits.groupBy("batch", "query_id").agg(F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias("r"))
    rows = per.groupBy("batch").agg(F.count("*").alias("queries"), F.sum("r").alias("r"))
    down = W.orderBy("batch").rowsBetween(W.unboundedPreceding, 0)
    return rows.select("batch", "queries", (F.col("r") / F.col("queries")).alias("recall"), (F.sum("r").over(down) / F.sum("queries").over(down)).alias("running"))


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and returns its rows from the shared folder, one folder a batch: no rows pass through
    the driver. In complete mode the last batch holds all of them."""
    spark = stream.sparkSession
    out, done = store.new_path(spark, "stream"), []

    def batch(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/{number}")
        done.append(number)

    run = stream.writeStream.foreachBatch(batch).outputMode(mode).option("checkpointLocation", store.new_path(spark, "checkpoint")).trigger(availableNow=True).start()
    run.awaitTermination()
    kept = sorted(set(done))[-1:] if mode == "complete" else sorted(set(done))
    return spark.read.schema(stream.schema).parquet(*[f"{out}/{n}" for n in kept]) if kept else spark.createDataFrame([], stream.schema)


def write_stream(stream: DataFrame, path: str, checkpoint: str):
    """Appends to Parquet; a restart goes on from the checkpoint."""
    return stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def _table_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table as a stream, whether it is one file or a folder."""
    return spark.readStream.schema(tables.SCHEMAS[name]).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/{name}.parquet*")


def stream_encode_query(spark: SparkSession, sf_dir: str, params: EncodeParams) -> DataFrame:
    """Packed bags arrive as a stream of files and are encoded as they arrive; the encodings are appended to a folder."""
    tokens = tables.fixed_tokens(tables.vector_tokens(spark, sf_dir))
    arriving = store.new_path(spark, "bags")
    tables.pack_bags(tokens, "fixed").repartition(4, "bag_id").write.parquet(arriving)
    stream = encode_stream(read_dir(spark, arriving, tables.BAGS, files=1), params)
    out = store.new_path(spark, "encoded")
    write_stream(stream, out, store.new_path(spark, "checkpoint")).awaitTermination()
    encoded = spark.read.schema(ENCODED).parquet(out)
    return to_arrays(encoded, params).select("bag_id", F.posexplode("enc").alias("place", "v"))


def stream_window_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily bags of each user's events; equal to the batch result, as no row is late here."""
    rows = finished(window_bags(_table_stream(spark, sf_dir, "events"), "1 day", "40 days"), "complete")
    return rows.select("user_id", F.unix_micros("window.start").alias("day_us"), "n", "s")


def stream_sliding_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-hour bags that start every hour."""
    rows = finished(window_bags(_table_stream(spark, sf_dir, "events"), "2 hours", "40 days", "1 hour"), "complete")
    return rows.select("user_id", F.unix_micros("window.start").alias("start_us"), "n", "s")


def stream_session_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions that half an hour without an event ends; equal to the batch way by windows."""
    rows = finished(session_counts(_table_stream(spark, sf_dir, "events"), "30 minutes", "40 days"), "complete")
    return rows.select("user_id", F.unix_micros("session_window.start").alias("began"), "n")


def stream_purchase_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The interval join of two streams; equal to the batch join."""
    return finished(views_to_purchases(_table_stream(spark, sf_dir, "events"), delay="40 days"))


def stream_distinct_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events that arrive twice are kept once."""
    rows = _table_stream(spark, sf_dir, "events").select("event_id", "ts")
    return finished(without_repeats(rows.union(_table_stream(spark, sf_dir, "events").select("event_id", "ts")), "40 days")).select("event_id")
