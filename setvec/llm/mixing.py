"""Mixing sources to target weights by repetition.

Words are counted per source, targets are shares of all words by weight, held to ``limit`` times a source's size with
the excess shared again among the others. A source's rate is its target over its size; each document is taken
floor(rate) times, and once more when its hash-seeded draw falls below the fraction. There are ``TRIALS`` seeds, each
with draws of its own; all are counted in one aggregation, and a source takes the one that brings it nearest its target.

A null text has size 0; a null source is a source, the last. Rows with equal ids share a draw. A source of size 0 has
target 0 and rate 0. An empty table gives no rows. ``repeated`` keeps all columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setvec.llm.common import documents, free_name, stored

WEIGHTS = (5, 2, 1)
LIMIT, SEED = 3, "mix-2"
#: Draws of which each source takes the one that comes nearest its target; more come nearer where documents are few.
TRIALS = 128
_SPAN = 1 << 40


def sized(docs: DataFrame) -> DataFrame:
    """doc_id, source, size: words are runs of bytes other than space and tab to carriage return."""
    words = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")
    return docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), words.alias("size"))


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT) -> DataFrame:
    """source, source_size, target, rate: the water level is found in one sort by the ratio of limit to weight.

    Held sources are those of the lowest ratios: the first place at which the level shared by the rest no longer lifts
    the next source above its limit ends them. The table has a row per source.
    """
    totals = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    listed = totals.withColumn("place", F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1)
    weight = F.expr(f"element_at(array({', '.join(map(str, weights))}), cast(place % {len(weights)} as int) + 1)")
    rows = listed.withColumn("weight", weight.cast("long")).withColumn("cap", F.col("source_size") * limit)
    up = W.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("place").asc())
    before, whole = up.rowsBetween(W.unboundedPreceding, -1), up.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    rows = rows.withColumns({
        "rest": F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0)),
        "rest_weight": F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0)),
    })
    rows = rows.withColumn("free", F.col("rest") * F.col("weight") <= F.col("cap") * F.col("rest_weight"))
    first = F.first(F.when(F.col("free"), F.struct("rest", "rest_weight")), ignorenulls=True)
    rows = rows.withColumns({"level": first.over(whole), "is_free": F.max("free").over(up.rowsBetween(W.unboundedPreceding, 0))})
    share = F.col("level.rest").cast("double") * F.col("weight") / F.col("level.rest_weight")
    target = F.when(F.col("is_free"), share).otherwise(F.col("cap").cast("double"))
    rows = rows.withColumn("target", target)
    rate = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(limit)))).otherwise(0.0)
    return rows.select("source", "source_size", "target", rate.alias("rate"))


def draws() -> F.Column:
    """Two whole numbers of 40 bits that hang on the seed and the id alone. Draw t of a document is low + t * high
    modulo 2^40, so that any two of its draws are independent."""
    key = F.md5(F.concat(F.lit(f"{SEED}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    part = lambda at: F.conv(F.substring(key, at, 10), 16, 10).cast("long")
    return F.struct(part(1).alias("low"), part(11).alias("high"))


def copies(rate: F.Column, trial: F.Column, drawn: F.Column) -> F.Column:
    """floor(rate), and one more if the draw of that trial falls below the fraction."""
    place = (drawn["low"] + trial * drawn["high"]) % F.lit(_SPAN)
    return (F.floor(rate) + (place / F.lit(float(_SPAN)) < rate - F.floor(rate)).cast("int")).cast("int")


def chosen_trials(sizes: DataFrame, targets: DataFrame) -> DataFrame:
    """source, source_size, target, rate, trial: of ``TRIALS`` draws the one whose words come nearest a source's target,
    ties to the first. Every task adds its words by source and trial before the shuffle, so a source with a third of all
    rows is no larger group than another."""
    right = targets.withColumnRenamed("source", "of")
    rows = sizes.where("size > 0").join(right, F.col("source").eqNullSafe(F.col("of"))).select("of", "size", "target", "rate", draws().alias("drawn"))
    rows = rows.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(TRIALS - 1))))
    words = rows.groupBy("of", "target", "trial").agg(F.sum(F.col("size") * copies(F.col("rate"), F.col("trial"), F.col("drawn"))).alias("words"))
    near = F.min_by("trial", F.struct(F.abs(F.col("words") - F.col("target")), F.col("trial"))).alias("trial")
    best = words.groupBy(F.col("of").alias("source")).agg(near)
    own = best.withColumnRenamed("source", "of")
    out = targets.join(own, F.col("source").eqNullSafe(F.col("of")), "left").drop("of")
    return out.withColumn("trial", F.coalesce("trial", F.lit(0)))


def with_copies(sizes: DataFrame, chosen: DataFrame) -> DataFrame:
    """Adds source_size, target, rate, trial and the number of copies to each document."""
    right = chosen.withColumnRenamed("source", "of")
    rows = sizes.join(right, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    return rows.withColumn("copies", copies(F.col("rate"), F.col("trial"), draws()))


def repeated(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT) -> DataFrame:
    """The mix itself: every document as often as it is taken, with all its columns. No text is shuffled unless the
    table of sources is too large to broadcast."""
    sizes = stored(sized(docs), "sizes")
    chosen = stored(chosen_trials(sizes, stored(source_targets(sizes, weights, limit), "targets")), "mix")
    of, rate, trial, n = (free_name(docs, x) for x in ("mix_source", "mix_rate", "mix_trial", "mix_n"))
    right = chosen.select(F.col("source").alias(of), F.col("rate").alias(rate), F.col("trial").alias(trial))
    rows = docs.join(right, F.col("source").cast("string").eqNullSafe(F.col(of)))
    taken = rows.withColumn(n, copies(F.col(rate), F.col(trial), draws())).where(F.col(n) > 0)
    taken = taken.withColumn(n, F.explode(F.sequence(F.lit(1), F.col(n))))
    return taken.select(*[F.col(f"`{c}`") for c in docs.columns])


def op5_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = stored(sized(documents(spark, sf_dir)), "sizes")
    chosen = stored(chosen_trials(sizes, stored(source_targets(sizes), "targets")), "mix")
    taken = (F.col("size") * F.col("copies")).alias("taken")
    return with_copies(sizes, chosen).select("doc_id", "size", "source_size", "target", taken, "copies", "source")


OP5_SQL = rf"""
WITH sizes AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
totals AS (SELECT source, sum(size)::BIGINT AS source_size FROM sizes GROUP BY source),
listed AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS place FROM totals),
capped AS (SELECT *, [5, 2, 1][(place % 3)::INT + 1]::BIGINT AS weight, {LIMIT} * source_size AS cap FROM listed),
running AS (
  SELECT *,
    (sum(source_size) OVER () - coalesce(sum(cap) OVER (up ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS rest,
    (sum(weight) OVER () - coalesce(sum(weight) OVER (up ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS rest_weight,
    row_number() OVER (up) AS nth
  FROM capped WINDOW up AS (ORDER BY cap::DOUBLE / weight, place)),
level AS (SELECT * FROM running WHERE rest * weight <= cap * rest_weight ORDER BY nth LIMIT 1),
targets AS (
  SELECT r.source, r.source_size,
    CASE WHEN r.nth >= l.nth THEN l.rest::DOUBLE * r.weight / l.rest_weight ELSE r.cap::DOUBLE END AS target
  FROM running r, level l),
rated AS (
  SELECT s.doc_id, s.size, t.source_size, t.target, s.source,
    CASE WHEN t.source_size > 0 THEN least(t.target / t.source_size, {LIMIT}.0::DOUBLE) ELSE 0.0::DOUBLE END AS rate,
    md5('{SEED}:' || coalesce(s.doc_id::VARCHAR, '')) AS h
  FROM sizes s JOIN targets t ON s.source IS NOT DISTINCT FROM t.source),
drawn AS (SELECT *, ('0x' || substr(h, 1, 10))::BIGINT AS low, ('0x' || substr(h, 11, 10))::BIGINT AS high FROM rated),
tried AS (
  SELECT source, target, t.i AS trial,
    sum(size * (floor(rate) + (((low + t.i * high) % {_SPAN})::DOUBLE / {_SPAN}::DOUBLE < rate - floor(rate))::INT))::BIGINT AS words
  FROM drawn, range({TRIALS}) t(i) WHERE size > 0 GROUP BY ALL),
nearest AS (
  SELECT source, trial FROM (SELECT source, trial, row_number() OVER (PARTITION BY source ORDER BY abs(words - target), trial) AS nth FROM tried)
  WHERE nth = 1),
counted AS (
  SELECT d.*, (floor(rate) + (((low + coalesce(n.trial, 0) * high) % {_SPAN})::DOUBLE / {_SPAN}::DOUBLE < rate - floor(rate))::INT)::INT AS copies
  FROM drawn d LEFT JOIN nearest n ON d.source IS NOT DISTINCT FROM n.source)
SELECT doc_id, size, source_size, target, size * copies AS taken, copies, source FROM counted
"""
