"""The given tables with declared schemas, bags made from them, checks at ingest, and stores."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from setvec.functions import vectors as V
from setvec.functions.seeds import int12_column
from setvec.plans.params import EncodeParams

SCALE = 1 << 20

SCHEMAS = {
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "pages": "page_id bigint, url string, html string",
    "events": "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, "
    "l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; the schema is declared, so no file is opened to find it."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def checked(rows: DataFrame, dim: int, column: str = "vec") -> DataFrame:
    """Adds ``reject_reason``: null for a vector that may be used."""
    v = F.col(column)
    bad = F.exists(v, lambda x: F.isnan(x) | (F.abs(x) == float("inf")))
    reason = F.when(v.isNull(), "null").when(F.size(v) != dim, "length").when(F.exists(v, lambda x: x.isNull()), "null component")
    return rows.withColumn("reject_reason", reason.when(bad, "not finite"))


def accepted(rows: DataFrame, dim: int, column: str = "vec") -> DataFrame:
    return checked(rows, dim, column).where("reject_reason is null").drop("reject_reason")


def vector_tokens(spark: SparkSession, sf_dir: str, size: int = 8) -> DataFrame:
    """bag_id, pos, vec: consecutive vectors of ``embeddings``, ``size`` to a bag."""
    rows = load(spark, sf_dir, "embeddings").where("embedding is not null")
    return rows.select(F.expr(f"vec_id div {size}").alias("bag_id"), F.expr(f"cast(vec_id % {size} as int)").alias("pos"), F.col("embedding").alias("vec"))


def fixed_tokens(tokens: DataFrame) -> DataFrame:
    """The same in whole numbers."""
    return tokens.withColumn("vec", V.vec_fixed("vec", SCALE))


#: Places of a planted query; a short or broken bag fills fewer.
PLANTED = 4


def planted_tokens(tokens: DataFrame, sigma: int = 1, seed: int = 42, vectors: int = PLANTED) -> DataFrame:
    """Queries near known bags: the first vectors of each bag with hash noise of ``sigma`` times a vector's length.
    Takes and gives fixed-point tokens; the query's bag is its source."""
    key = lambda i: F.concat_ws(":", F.lit("noise"), F.lit(str(seed)), F.col("bag_id").cast("string"), F.col("pos").cast("string"), i.cast("string"))
    noisy = F.transform("vec", lambda x, i: x + int12_column(key(i)) * (256 * sigma))
    return tokens.where(F.col("pos") < vectors).withColumn("vec", noisy)


def heldout_tokens(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Queries: every tenth vector, grouped by label; documents: the others by tens."""
    rows = load(spark, sf_dir, "embeddings").where("embedding is not null")
    own = rows.where("vec_id % 10 = 0").select(F.col("label").cast("long").alias("bag_id"), F.expr("cast(vec_id div 10 as int)").alias("pos"), F.col("embedding").alias("vec"))
    rest = rows.where("vec_id % 10 <> 0").select(F.expr("vec_id div 10").alias("bag_id"), F.expr("cast(vec_id % 10 as int)").alias("pos"), F.col("embedding").alias("vec"))
    return own, rest


def _packing(kind: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for batch in batches:
            ids, ns, raws = [], [], []
            for bag, items in zip(batch.column("bag_id"), batch.column("items"), strict=True):
                rows = items.as_py()
                ids.append(bag.as_py())
                ns.append(len(rows))
                raws.append(np.array([r["vec"] for r in rows], V.KINDS[kind]).tobytes())
            yield pa.record_batch([pa.array(ids, pa.int64()), pa.array(ns, pa.int32()), pa.array(raws, pa.binary())], names=["bag_id", "n", "vecs"])

    return run


BAGS = "bag_id bigint, n int, vecs binary"


def pack_bags(tokens: DataFrame, kind: str = "float") -> DataFrame:
    """One row per bag, its vectors in order of ``pos``: the one shuffle of the engine, done once at ingest."""
    items = F.array_sort(F.collect_list(F.struct("pos", "vec"))).alias("items")
    return tokens.groupBy("bag_id").agg(items).mapInArrow(_packing(kind), BAGS)


def write_bags(bags: DataFrame, path: str, buckets: int = 64) -> None:
    """Packed bags clustered by id, so that a re-rank reads few row groups."""
    bags.repartition(buckets, "bag_id").sortWithinPartitions("bag_id").write.parquet(path)


def write_encodings(encodings: DataFrame, path: str, params: EncodeParams, by: str | None = None) -> None:
    """Encodings with the settings they were made by, partitioned by ``by`` if given."""
    out = encodings.withColumn("params", F.lit(params.to_json())).write
    (out.partitionBy(by) if by else out).parquet(path)


def read_encodings(spark: SparkSession, path: str, params: EncodeParams) -> DataFrame:
    """Refuses encodings of other settings: their products would mean nothing."""
    rows = spark.read.parquet(path)
    other = rows.where(F.col("params") != params.to_json()).select("params").first()
    if other is not None:
        raise ValueError(f"encodings were made with {other['params']}")
    return rows.drop("params")


def write_ranked(ranked: DataFrame, path: str, form: str = "parquet") -> None:
    """Ranked lists (query_id, rank, doc_id, score) as parquet, json or csv."""
    ranked.write.format(form).option("header", True).save(path)


def read_bags(spark: SparkSession, path: str, form: str = "json") -> DataFrame:
    """Tokens (bag_id, pos, vec) from JSON lines, from CSV or text whose vectors are numbers joined by spaces, or from
    parquet."""
    vec = T.StructType.fromDDL("bag_id bigint, pos int, vec array<float>")
    if form == "json":
        return spark.read.schema(vec).json(path)
    if form == "parquet":
        return spark.read.schema(vec).parquet(path)
    if form == "csv":
        rows = spark.read.schema("bag_id bigint, pos int, vec string").csv(path, header=True)
    elif form == "text":
        cut = F.split("value", "\t")
        rows = spark.read.text(path).select(cut[0].cast("long").alias("bag_id"), cut[1].cast("int").alias("pos"), cut[2].alias("vec"))
    else:
        raise ValueError(f"no reader for {form!r}")
    return rows.withColumn("vec", F.split("vec", " ").cast("array<float>"))
