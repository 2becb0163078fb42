"""Token ids in canonical length-limited Huffman code, in independent blocks with bit-offset checkpoints.

A file set is a Parquet folder of blocks and a header of code lengths. Global id counts give the code lengths, limited
by package-merge; lengths alone fix the canonical code. A block holds whole documents, its ids' bits, and the bit offset
of every ``STEP``-th id, so that a block is decoded on its own and its runs side by side, each step one table look-up
for all runs. Documents lie in ascending order of id, blocks in the order of their first document.

A null text is the empty text: one end id. Repeated rows are stored each; equal ids lie next to each other, equal
texts first. An empty table gives an empty file set. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setvec.llm.common import bounded_batches, documents, new_path, rows_out, slices, small, stored, texts_of
from setvec.llm.tokens import END_ID, coder

LONGEST, STEP, BLOCK_IDS = 16, 256, 1 << 18
#: Parts whose places are broadcast at most, 12 bytes each; more meet their blocks by a shuffle.
PARTS = 1_000_000
_BLOCKS = pa.schema(
    [("part", pa.int32()), ("block", pa.int32()), ("n_ids", pa.int64()), ("part_ids", pa.int64())]
    + [("doc_ids", pa.binary()), ("doc_tokens", pa.binary()), ("checkpoints", pa.binary()), ("bits", pa.binary())]
    + [("bits_crc32", pa.int64())]
)
BLOCK_DDL = (
    "part int, block int, n_ids bigint, part_ids bigint, doc_ids binary, doc_tokens binary, checkpoints binary, "
    "bits binary, bits_crc32 bigint"
)
_RAW = pa.schema(
    [("part", pa.int32()), ("block", pa.int32()), ("n_ids", pa.int64()), ("part_ids", pa.int64())]
    + [(n, pa.binary()) for n in ("doc_ids", "doc_tokens", "ids")]
)
RAW_DDL = "part int, block int, n_ids bigint, part_ids bigint, doc_ids binary, doc_tokens binary, ids binary"
_READ = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "n_tokens", "ids_crc32")])
READ_DDL = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"


def code_lengths(counts: np.ndarray, longest: int = LONGEST) -> np.ndarray:
    """Lengths of an optimal prefix code with none over ``longest``, by package-merge; 0 for ids that don't occur."""
    used = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.uint8)
    if len(used) <= 1:
        out[used] = 1
        return out
    if len(used) > 1 << longest:
        raise ValueError(f"{len(used)} ids don't fit codes of {longest} bits")
    order = used[np.argsort(counts[used], kind="stable")]
    weight, n = counts[order].astype(np.int64), len(order)
    merged: list[np.ndarray] = []
    now = weight
    for _ in range(longest - 1):
        pairs = now[: len(now) // 2 * 2].reshape(-1, 2).sum(1)
        both = np.concatenate([weight, pairs])
        sort = np.argsort(both, kind="stable")
        merged.append(sort < n)
        now = both[sort]
    take = 2 * n - 2
    lengths = np.zeros(n, np.int64)
    for is_leaf in reversed(merged):
        leaves = int(is_leaf[:take].sum())
        lengths[:leaves] += 1
        take = 2 * (take - leaves)
    lengths[:take] += 1
    out[order] = lengths
    return out


def canonical(lengths: np.ndarray) -> np.ndarray:
    """The code of each id: counted up by length and then id."""
    codes, code, before = np.zeros(len(lengths), np.uint32), 0, 0
    used = np.flatnonzero(lengths)
    for i in used[np.lexsort((used, lengths[used]))]:
        code <<= int(lengths[i]) - before
        codes[i], before = code, int(lengths[i])
        code += 1
    return codes


def tables(lengths: np.ndarray, longest: int = LONGEST) -> tuple[np.ndarray, np.ndarray]:
    """For each value of the next ``longest`` bits: the id and its length."""
    codes, ids, steps = canonical(lengths), np.zeros(1 << longest, np.uint32), np.zeros(1 << longest, np.uint8)
    used = np.flatnonzero(lengths)
    used = used[np.argsort(codes[used].astype(np.int64) << (longest - lengths[used].astype(np.int64)))]
    span = 1 << (longest - lengths[used].astype(np.int64))
    filled = int(span.sum())
    ids[:filled], steps[:filled] = np.repeat(used, span), np.repeat(lengths[used], span)
    return ids, steps


def pack_bits(ids: np.ndarray, lengths: np.ndarray, codes: np.ndarray) -> tuple[bytes, np.ndarray]:
    """Bits of the ids, most significant first, and the bit offset of every STEP-th id."""
    size = lengths[ids].astype(np.int64)
    at = np.cumsum(size) - size
    word, shift = at >> 5, at & 31
    value = codes[ids].astype(np.uint64) << (64 - size - shift).astype(np.uint64)
    n = int((at[-1] + size[-1] + 31) >> 5) + 1 if len(ids) else 1
    high = np.bincount(word, (value >> np.uint64(32)).astype(np.float64), n + 1)
    high[1:] += np.bincount(word, (value & np.uint64(0xFFFFFFFF)).astype(np.float64), n + 1)[:-1]
    return high[:n].astype(np.uint64).astype(">u4").tobytes(), at[::STEP]


def unpack_bits(bits: bytes, checkpoints: np.ndarray, n: int, table: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The ids again: all runs between checkpoints go forward together."""
    ids, steps = table
    words = np.concatenate([np.frombuffer(bits, ">u4").astype(np.uint64), np.zeros(2, np.uint64)])
    wide = (words[:-1] << np.uint64(32)) | words[1:]
    out, at = np.zeros((len(checkpoints), STEP), np.uint32), checkpoints.astype(np.int64)
    last = n - STEP * (len(checkpoints) - 1)
    down = np.int64(64 - LONGEST)
    for k in range(STEP):
        if k == last:
            at = at[:-1]
        if not len(at):
            break
        key = (wide[at >> 5] >> (down - (at & 31)).astype(np.uint64)) & np.uint64((1 << LONGEST) - 1)
        out[: len(at), k] = ids[key]
        at = at + steps[key]
    return out.reshape(-1)[:n]


def raw_blocks(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Blocks of plain ids in ascending order of documents. Texts are dealt by range of doc_id once, sorted, coded and
    gathered in the same stage; a block is one row, so later readers may split or join files as they like."""

    end = np.array([END_ID], "<u4").tobytes()

    def row(nth: int, before: int, docs: list, counts: list, ids: list) -> pa.RecordBatch:
        names = np.array([np.iinfo(np.int64).min if x is None else x for x in docs], "<i8")
        return rows_out(
            _RAW, part=[TaskContext.get().partitionId()], block=[nth], n_ids=[sum(counts)], part_ids=[before], doc_ids=[names.tobytes()],
            doc_tokens=[np.array(counts, "<i8").tobytes()], ids=[b"".join(ids)],
        )

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = coder(tokenizer)
        kind = "<u2" if got.size <= 1 << 16 else "<u4"
        docs, counts, held, n, nth, before = [], [], [], 0, 0, 0
        for part in (part for batch in batches for part in slices(batch)):
            for doc, raw in zip(part.column("doc_id").to_pylist(), got.encode(texts_of(part)), strict=True):
                if n >= BLOCK_IDS:
                    yield row(nth, before, docs, counts, held)
                    docs, counts, held, n, nth, before = [], [], [], 0, nth + 1, before + n
                ids = np.frombuffer(raw + end, "<u4")
                docs.append(doc)
                counts.append(len(ids))
                held.append(ids.astype(kind).tobytes())
                n += len(ids)
        if docs:
            yield row(nth, before, docs, counts, held)

    bounded_batches(docs.sparkSession)
    # Texts are dealt before they are coded: finding the ranges reads the ids alone and codes nothing.
    rows = docs.select(F.col("doc_id").cast("long"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(gather, RAW_DDL)


def _as_ids(raw: bytes, n: int) -> np.ndarray:
    return np.frombuffer(raw, "<u2" if len(raw) == 2 * n else "<u4").astype(np.int64)


def id_counts(blocks: DataFrame, size: int) -> np.ndarray:
    """How often each id occurs; a row per id reaches the driver, at most the vocabulary's size."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for batch in batches:
            for n, raw in zip(batch.column("n_ids").to_pylist(), batch.column("ids").to_pylist(), strict=True):
                total += np.bincount(_as_ids(raw, n), minlength=size)
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at), pa.array(total[at])], names=["id", "n"])

    found = blocks.select("n_ids", "ids").mapInArrow(count, "id bigint, n bigint").groupBy("id").agg(F.sum("n").alias("n"))
    out = np.zeros(size, np.int64)
    got = found.toPandas()
    out[got["id"].to_numpy(np.int64)] = got["n"].to_numpy(np.int64)
    return out


def write_ids(docs: DataFrame, path: str, tokenizer: str | None = None) -> None:
    """Writes ``path``/header, ``path``/blocks and ``path``/parts. Texts are coded by the tokenizer once.

    A part is what one task wrote, and a block knows the ids before it in its part. So the parts' table, a row of two
    numbers a task, is all that is ordered as a whole, and no block is moved to learn its place."""
    spark = docs.sparkSession
    raw = stored(raw_blocks(docs, tokenizer), "ids")
    lengths = code_lengths(id_counts(raw, coder(tokenizer).size))
    head = spark.createDataFrame([(LONGEST, STEP, bytearray(lengths.tobytes()))], "longest int, step int, lengths binary")
    head.coalesce(1).write.parquet(f"{path}/header")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = canonical(lengths)
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                bits, marks = pack_bits(_as_ids(row.column("ids")[0].as_py(), row.column("n_ids")[0].as_py()), lengths, codes)
                same = {c: row.column(c) for c in ("part", "block", "n_ids", "part_ids", "doc_ids", "doc_tokens")}
                yield rows_out(_BLOCKS, checkpoints=[marks.astype("<u4").tobytes()], bits=[bits], bits_crc32=[zlib.crc32(bits)], **same)

    raw.mapInArrow(encode, BLOCK_DDL).write.parquet(f"{path}/blocks")
    sizes = spark.read.schema(BLOCK_DDL).parquet(f"{path}/blocks").groupBy("part").agg(F.sum("n_ids").alias("n_ids"))
    up = W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    sizes.select("part", F.coalesce(F.sum("n_ids").over(up), F.lit(0)).alias("parts_ids")).write.parquet(f"{path}/parts")


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """Decodes every block: doc_id, start (the ids of all documents before), n_tokens, ids_crc32."""
    head = spark.read.parquet(f"{path}/header").first()
    lengths = np.frombuffer(bytes(head["lengths"]), np.uint8)

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = tables(lengths, head["longest"])
        for batch in batches:
            for r in batch.to_pylist():
                if zlib.crc32(r["bits"]) != r["bits_crc32"]:
                    raise ValueError(f"block {r['part']}:{r['block']} is damaged")
                ids = unpack_bits(r["bits"], np.frombuffer(r["checkpoints"], "<u4"), r["n_ids"], table).astype("<u4")
                counts = np.frombuffer(r["doc_tokens"], "<i8")
                names = np.frombuffer(r["doc_ids"], "<i8")
                ends = np.cumsum(counts)
                raw = ids.tobytes()
                sums = [zlib.crc32(raw[4 * (b - c) : 4 * b]) for b, c in zip(ends.tolist(), counts.tolist(), strict=True)]
                lost = names == np.iinfo(np.int64).min
                yield rows_out(
                    _READ, doc_id=pa.array(names, mask=lost), start=r["parts_ids"] + r["part_ids"] + ends - counts,
                    n_tokens=counts, ids_crc32=sums,
                )

    files = spark.read.schema(BLOCK_DDL).parquet(f"{path}/blocks")
    parts = spark.read.schema("part int, parts_ids bigint").parquet(f"{path}/parts")
    return files.join(small(parts, PARTS), "part").mapInArrow(decode, READ_DDL)


def op7_huffman_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "huffman")
    write_ids(documents(spark, sf_dir), path)
    return read_ids(spark, path)
