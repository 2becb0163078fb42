"""Packing by the length histogram, shortest pack first.

Documents become ids with an end id. A document longer than a sequence is cut into whole sequences and a rest. Only the
histogram of rest lengths reaches the driver (at most ``width - 1`` counts). Lengths are placed longest first: each goes
to the pattern with the smallest total that still has room, as many at a time as the counts allow, and opens patterns
when none has room. Patterns are then joined back to the documents by the rank of a rest among those of its length.

A null text is the empty text, whose one piece holds the end id. Repeated rows are packed each on its own. An empty
table gives no rows; other columns are ignored. Ranks are dealt by id and then start, so ties don't matter.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, documents, rows_out, stored, texts_of
from setvec.llm.tokens import END_ID, coder

WIDTH = 2048
PIECE_DDL = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"
_PIECES = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")])


def pieces(docs: DataFrame, width: int = WIDTH, tokenizer: str | None = None) -> DataFrame:
    """Each document's pieces of at most ``width`` ids: doc_id, start, length, ids_crc32, doc_tokens."""
    end = np.array([END_ID], "<u4").tobytes()

    def cut(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        rows = []
        for doc, raw in zip(batch.column("doc_id").to_pylist(), coder(tokenizer).encode(texts_of(batch)), strict=True):
            raw += end
            for a in range(0, len(raw), 4 * width):
                part = raw[a : a + 4 * width]
                rows.append((doc, a // 4, len(part) // 4, zlib.crc32(part), len(raw) // 4))
        columns = zip(*rows, strict=True)
        yield rows_out(_PIECES, **dict(zip(_PIECES.names, columns, strict=True)))

    return arrow_map(docs.select(F.col("doc_id").cast("long"), "text"), cut, PIECE_DDL)


def shortest_pack_first(histogram: dict[int, int], width: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths, longest first) with how often each is used. Uses every length exactly as often as counted."""
    open_by_room: dict[int, dict[tuple[int, ...], int]] = {}
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        room = max(open_by_room, default=0)
        while left and room >= length:
            packs = open_by_room[room]
            pattern, count = packs.popitem()
            used = min(left, count)
            if count > used:
                packs[pattern] = count - used
            if not packs:
                del open_by_room[room]
            place = open_by_room.setdefault(room - length, {})
            place[(*pattern, length)] = place.get((*pattern, length), 0) + used
            left -= used
            room = max(open_by_room, default=0)
        if left:
            place = open_by_room.setdefault(width - length, {})
            place[(length,)] = place.get((length,), 0) + left
    return sorted((p, n) for packs in open_by_room.values() for p, n in packs.items())


def slots(patterns: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """For each length, runs of ranks: (length, first rank, last rank, sequence of the first, offset)."""
    used: dict[int, int] = {}
    out, sequence = [], 0
    for pattern, count in patterns:
        offset = 0
        for length in pattern:
            low = used.get(length, 0)
            out.append((length, low, low + count - 1, sequence, offset))
            used[length] = low + count
            offset += length
        sequence += count
    return out


def ranked(rows: DataFrame) -> DataFrame:
    """Ranks from 0 within each length, without gathering a length's rows in one task.

    Rows are dealt by range of (length, id, start) and written; a row's rank is its place in its own partition plus the
    counts of the partitions before it, which come from a table of a row per partition and length.
    """
    spread = rows.repartitionByRange("length", "doc_id", "start").withColumn("part", F.spark_partition_id())
    spread = stored(spread, "pieces")
    counts = spread.groupBy("length", "part").count()
    before = F.sum("count").over(W.partitionBy("length").orderBy("part")) - F.col("count")
    counts = counts.select("length", "part", before.alias("before"))
    near = F.row_number().over(W.partitionBy("length", "part").orderBy("doc_id", "start", "ids_crc32")) - 1
    out = spread.withColumn("near", near).join(counts, ["length", "part"])
    return out.withColumn("rank", F.col("before") + F.col("near")).drop("part", "near", "before")


def packed(docs: DataFrame, width: int = WIDTH, tokenizer: str | None = None) -> DataFrame:
    """Every piece with its sequence and offset. Whole sequences come after the packed ones."""
    spark = docs.sparkSession
    rows = stored(ranked(stored(pieces(docs, width, tokenizer), "cut")), "ranked")
    histogram = {r["length"]: r["n"] for r in rows.groupBy("length").agg(F.count("*").alias("n")).collect()}
    histogram.pop(width, None)
    patterns = shortest_pack_first(histogram, width)
    first_whole = sum(n for _, n in patterns)
    table = [*slots(patterns), (width, 0, 2**62, first_whole, 0)]
    names = "length bigint, low bigint, high bigint, base bigint, offset bigint"
    # A pattern ends or begins where a length runs out, so the table's rows grow with the width, not with the corpus.
    where = F.broadcast(spark.createDataFrame(table, names))
    hit = (rows["length"] == where["length"]) & (rows["rank"] >= where["low"]) & (rows["rank"] <= where["high"])
    sequence = (F.col("base") + F.col("rank") - F.col("low")).alias("sequence_id")
    return rows.join(where, hit).select("doc_id", "start", rows["length"], "ids_crc32", "doc_tokens", sequence, "offset")


def op9_shortest_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(documents(spark, sf_dir))
