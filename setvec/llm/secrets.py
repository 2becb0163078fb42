"""Secret scans over an incremental ledger of content-addressed blobs.

Every text (a historical version of a path) has the SHA-256 of its bytes as its blob. The ledger holds, for each scanned
blob, the rule versions that were scanned and their findings; it is a folder of generations, one for each scan. A scan
takes only pairs of blob and rule version that the ledger lacks, one text for each blob, adds them as a generation, and
joins the findings of all generations back to every path that holds the blob.

A null text is the empty text. Spans are code points, end exclusive, of whole matches. Repeated rows are repeated paths
and stay; equal starts are ordered by kind as listed; an empty table gives no rows; other columns are ignored or, in
``redacted``, kept.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, documents, free_name, new_path, rows_out, stored, texts_of

# The kinds, in their order, with each one's pattern, the group that is measured and its least length.
RULES = (
    ("assign", r"""(?ai:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]{32,}", 0, 32),
    ("private_key", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----", 0, 1),
    ("web_token", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 1),
    ("host_token", r"(?<![A-Za-z0-9])gh[opsu]_[A-Za-z0-9]{36,}", 0, 1),
    ("chat_token", r"(?<![A-Za-z0-9])xox[abprs]-[A-Za-z0-9-]{10,}", 0, 1),
    ("url_login", r"[a-z][a-z0-9+.-]{1,15}://[^\s:/@]{1,64}:[^\s:/@]{3,64}@", 0, 1),
)
BASE = ("assign", "access", "hex")
#: Spans that are broadcast at most (a blob counts as eight), 12 bytes each; more meet their texts by a shuffle.
SPANS = 1_000_000
#: New blobs that are broadcast at most, about 100 bytes each; with more, all texts of the table are shuffled.
BLOBS = 200_000
SALTS = 16
#: A rule's version: raise its number when its pattern changes, and only its pairs are scanned anew.
VERSIONS = {kind: f"{kind}@1" for kind, *_ in RULES}

LEDGER_DDL = "blob string, scanned array<string>, found array<struct<rule_version:string,starts:array<int>,ends:array<int>>>"
_FOUND = pa.struct([("rule_version", pa.string()), ("starts", pa.list_(pa.int32())), ("ends", pa.list_(pa.int32()))])
_FIELDS = pa.schema([("blob", pa.string()), ("scanned", pa.list_(pa.string())), ("found", pa.list_(_FOUND))])
_COMPILED = {kind: (re.compile(pattern), group, least) for kind, pattern, group, least in RULES}
#: A text without the literal holds no match of the kind; the search for it is far cheaper.
_NEEDS = {
    "access": "AKIA", "private_key": "PRIVATE KEY-----", "web_token": "eyJ", "host_token": "gh", "chat_token": "xox", "url_login": "://",
}


def spans(text: str, kind: str) -> list[tuple[int, int]]:
    """Leftmost matches that don't overlap; those whose measured group is too short are dropped after matching."""
    if (need := _NEEDS.get(kind)) and need not in text:
        return []
    pattern, group, least = _COMPILED[kind]
    return [m.span() for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]


def _scan(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    scanned, found = [], []
    for text, todo in zip(texts_of(batch), batch.column("kinds").to_pylist(), strict=True):
        hits = [(VERSIONS[kind], spans(text, kind)) for kind in todo]
        scanned.append([VERSIONS[kind] for kind in todo])
        found.append([{"rule_version": v, "starts": [a for a, _ in s], "ends": [b for _, b in s]} for v, s in hits if s])
    yield rows_out(_FIELDS, blob=batch.column("blob"), scanned=scanned, found=found)


def paths_of(docs: DataFrame, path: str = "doc_id") -> DataFrame:
    """One row for each path and version: path, blob."""
    return docs.select(F.col(path).alias("path"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("blob"))


def unseen(docs: DataFrame, ledger: DataFrame | None, kinds: tuple[str, ...]) -> DataFrame:
    """One text for each blob that lacks a rule version in the ledger, with the kinds still to scan.

    Copies meet in a partial aggregation, so a blob with a third of all rows leaves each map task once. With a ledger,
    hashes are compared first; where few blobs are new, only their texts are shuffled.
    """
    texts = docs.select(F.sha2(F.coalesce("text", F.lit("")), 256).alias("blob"), F.coalesce("text", F.lit("")).alias("text"))
    if ledger is None:
        return texts.dropDuplicates(["blob"]).withColumn("kinds", F.array(*map(F.lit, kinds)))
    done = ledger.groupBy("blob").agg(F.array_distinct(F.flatten(F.collect_list("scanned"))).alias("done"))
    todo = F.array(*[F.when(~F.array_contains("done", VERSIONS[k]), F.lit(k)) for k in kinds])
    known = texts.select("blob").distinct().join(done, "blob", "left").withColumn("done", F.coalesce("done", F.array().cast("array<string>")))
    new = stored(known.select("blob", F.array_compact(todo).alias("kinds")).where(F.size("kinds") > 0), "unseen")
    if new.count() <= BLOBS:
        return texts.join(F.broadcast(new), "blob").dropDuplicates(["blob"]).select("blob", "text", "kinds")
    return texts.dropDuplicates(["blob"]).join(new, "blob").select("blob", "text", "kinds")


def scan(docs: DataFrame, ledger: DataFrame | None = None, kinds: tuple[str, ...] = tuple(VERSIONS)) -> DataFrame:
    """Ledger rows of what is scanned now: a row for each blob with a pair that ``ledger`` lacks, with or without findings."""
    return arrow_map(unseen(docs, ledger, kinds), _scan, LEDGER_DDL)


def generations(spark: SparkSession, path: str) -> list[int]:
    """Finished generations of a stored ledger, oldest first; none where there is no folder."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = folder.getFileSystem(spark._jsc.hadoopConfiguration())
    if not files.exists(folder):
        return []
    whole = lambda f: files.exists(spark._jvm.org.apache.hadoop.fs.Path(f.getPath(), "_SUCCESS"))
    return sorted(int(f.getPath().getName().partition("-")[2]) for f in files.listStatus(folder) if f.getPath().getName().startswith("generation-") and whole(f))


def read_ledger(spark: SparkSession, path: str) -> DataFrame | None:
    """All rows of a stored ledger, or None if nothing was ever scanned into it."""
    found = [f"{path}/generation-{n}" for n in generations(spark, path)]
    return spark.read.schema(LEDGER_DDL).parquet(*found) if found else None


def update(docs: DataFrame, path: str, kinds: tuple[str, ...] = tuple(VERSIONS)) -> DataFrame:
    """Scans what the ledger at ``path`` lacks, adds it as the next generation, and returns the whole ledger as read back.

    A generation counts when its write has ended; one that broke off is written anew by the next scan."""
    spark = docs.sparkSession
    before = generations(spark, path)
    rows = scan(docs, read_ledger(spark, path), kinds)
    rows.write.mode("overwrite").parquet(f"{path}/generation-{before[-1] + 1 if before else 0}")
    return read_ledger(spark, path)


def by_blob(ledger: DataFrame) -> DataFrame:
    """All spans of each blob under the present rule versions, in one array of (start, place of the kind, end), ordered."""
    kinds = F.array(*[F.lit(VERSIONS[k]) for k in VERSIONS])
    hits = ledger.where(F.size("found") > 0).select("blob", F.explode("found").alias("f"))
    hits = hits.select("blob", F.array_position(kinds, F.col("f.rule_version")).cast("int").alias("nth"), F.explode(F.arrays_zip("f.starts", "f.ends")).alias("s"))
    span = F.struct(F.col("s.starts").alias("start"), "nth", F.col("s.ends").alias("end"))
    return hits.where("nth > 0").groupBy("blob").agg(F.array_sort(F.collect_set(span)).alias("found"))


def with_spans(rows: DataFrame, key: str, found: DataFrame) -> DataFrame:
    """``rows`` with the spans of the blob in column ``key``, null where there are none. Few spans are broadcast; many meet
    the rows by blob and salt, so that rows of one blob are dealt to ``SALTS`` tasks."""
    if (found.agg(F.sum(F.size(found.columns[1]) + 8)).first()[0] or 0) <= SPANS:
        return rows.join(F.broadcast(found), key, "left")
    salt = free_name(rows, "salt")
    dealt = rows.withColumn(salt, F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int"))
    right = found.withColumn(salt, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return dealt.join(right, [key, salt], "left").drop(salt)


def joined(found: str, keep: str = "true") -> F.Column:
    names = "array(" + ", ".join(f"'{k}'" for k in VERSIONS) + ")"
    one = f"concat(element_at({names}, x.nth), ':', x.start, ':', x.end)"
    return F.expr(f"array_join(transform(filter({found}, x -> {keep}), x -> {one}), ',')")


def findings_by_path(docs: DataFrame, ledger: DataFrame) -> DataFrame:
    """Every path with its blob's spans (an empty array where nothing was found)."""
    empty = F.array().cast("array<struct<start:int,nth:int,end:int>>")
    rows = with_spans(paths_of(docs), "blob", stored(by_blob(ledger), "found"))
    return rows.select("path", "blob", F.coalesce("found", empty).alias("found"))


def redacted(docs: DataFrame, ledger: DataFrame) -> DataFrame:
    """The documents with every span replaced by ``[kind]`` in angle brackets; overlapping spans merge into one.

    All columns stay; ``n_chars`` is counted anew where the table has it.
    """
    names = "array(" + ", ".join(f"'{k}'" for k in VERSIONS) + ")"
    whole, key, spots = (free_name(docs, x) for x in ("whole_text", "blob_key", "spots"))
    merge = (
        f"aggregate({spots}, named_struct('at', 0, 'out', ''), (a, x) -> if(x.end <= a.at, a, named_struct('at', x.end, 'out', "
        f"concat(a.out, substring({whole}, a.at + 1, greatest(0, x.start - a.at)), if(x.start < a.at, '', concat('<', element_at({names}, x.nth), '>'))))), "
        f"a -> concat(a.out, substring({whole}, a.at + 1)))"
    )
    marked = docs.withColumn(whole, F.coalesce("text", F.lit(""))).withColumn(key, F.sha2(whole, 256))
    marked = with_spans(marked, key, stored(by_blob(ledger).select(F.col("blob").alias(key), F.col("found").alias(spots)), "found"))
    new = F.when(F.col(spots).isNull(), F.col("text")).otherwise(F.expr(merge))
    kept = [new.alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns]
    out = marked.select(*kept)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def op3_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    rows = findings_by_path(docs, update(docs, new_path(spark, "ledger")))
    count = lambda kind: F.expr(f"size(filter(found, x -> x.nth = {BASE.index(kind) + 1}))").cast("long")
    return rows.select(
        F.col("path").cast("long").alias("doc_id"), *[count(k).alias(f"n_{k}") for k in BASE],
        F.sha2(joined("found", "x.nth <= 3"), 256).alias("base_sha256"), joined("found").alias("spans"), "blob",
    )
