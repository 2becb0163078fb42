"""Quality classifier: naive Bayes support vectors on n-gram indicators.

Features of a text are indicators of hashed n-grams: bytes (one to three) and character classes (three to five), plus
marks for words that repeat the word or two words before them and lines that repeat an earlier line. Counts per class
over all learning rows give each feature's log-count ratio; indicators are scaled by it and each text's vector to unit
length; a linear hinge-loss model is fitted by dual coordinate descent on a hash sample of at most ``SAMPLE`` learning
rows (a documented bound), one fifth of which only sets the sigmoid that turns margins into scores.

A null text is the empty text; its score is the sigmoid of the intercept. Several labels of one document count each.
With one class or no labels every score is that class's share (0.5 without any). Repeated rows stay, an empty table
gives no rows, and other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, bounded_batches, documents, held_fold, rows_out, slices, small, text_bytes
from setvec.llm.shingles import span_hashes, word_hashes

BITS, PARTS = 17, 64
SAMPLE, ROUNDS, COST, CUT = 4000, 12, 1.0, 0.3
#: Labels that are broadcast at most, 12 bytes each; more are joined by a shuffle.
LABELS = 500_000
MARKS = 4
SIZE = (1 << BITS) + MARKS

# Character classes of bytes; other marks stand for themselves.
_CLASS = np.arange(256, dtype=np.uint32)
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58], _CLASS[128:] = 97, 65, 48, 233

_FIELDS = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])
DDL = "doc_id bigint, held_out boolean, score double, predicted int"


def _hashed(v: np.ndarray, salt: int) -> np.ndarray:
    x = (v ^ np.uint32(salt * 0x9E3779B1 & 0xFFFFFFFF)) * np.uint32(0x85EBCA6B)
    x ^= x >> np.uint32(13)
    return x * np.uint32(0xC2B2AE35) >> np.uint32(32 - BITS)


def features(column: pa.Array) -> Iterator[np.ndarray]:
    """For each row its features, ascending."""
    raw, starts, lengths = text_bytes(column)
    x, c = raw.astype(np.uint32), _CLASS[raw]
    ahead = lambda v, k: np.concatenate([v[k:], np.zeros(min(k, len(v)), np.uint32)])
    two = x | ahead(x, 1) << np.uint32(8)
    three = two | ahead(x, 2) << np.uint32(16)
    codes = [(1, _hashed(x, 1)), (2, _hashed(two, 2)), (3, _hashed(three, 3))]
    run = c
    for k in range(1, 5):
        run = run * np.uint32(257) + ahead(c, k)
        if k >= 2:
            codes.append((k + 1, _hashed(run, 10 + k)))
    words, owner = word_hashes(column, lower=False)
    edges = np.searchsorted(owner, np.arange(len(column) + 1))
    same = np.concatenate([[False], words[1:] == words[:-1]])[: len(words)]
    again = np.concatenate([[False, False], words[2:] == words[:-2]])[: len(words)] if len(words) > 2 else np.zeros(len(words), bool)
    flags = np.zeros(SIZE, bool)
    for i in range(len(column)):
        a, n = int(starts[i]), int(lengths[i])
        flags[:] = False
        for width, code in codes:
            if n >= width:
                flags[code[a : a + n - width + 1]] = True
        lo, hi = edges[i], edges[i + 1]
        s, g = same[lo + 1 : hi], again[lo + 2 : hi]
        flags[-4] = bool((s[1:] & s[:-1]).any()) if len(s) > 1 else False
        flags[-3] = s.mean() > 0.2 if len(s) else False
        flags[-2] = g.mean() > 0.2 if len(g) else False
        cuts = np.flatnonzero(raw[a : a + n] == 10)
        if len(cuts):
            lines = span_hashes(raw[a : a + n], np.concatenate([[0], cuts + 1]), np.concatenate([cuts, [n]]))
            flags[-1] = len(np.unique(lines)) < 0.7 * len(lines)
        yield np.flatnonzero(flags).astype(np.int32)


@dataclass
class Model:
    weights: np.ndarray
    ratio: np.ndarray
    bias: float
    slope: float
    level: float

    def margin(self, at: np.ndarray) -> float:
        length = float(np.sqrt(np.square(self.ratio[at]).sum()))
        return float(self.weights[at].sum()) / length + self.bias if length else self.bias

    def score(self, at: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.slope * self.margin(at) + self.level, -30, 30))))


def class_counts(rows: DataFrame) -> np.ndarray:
    """Features by class (two rows) over all rows (text, quality), and the rows of each class as a last column. A task
    sends its sums in slices; 2 * SIZE counts reach the driver."""
    bounded_batches(rows.sparkSession)
    width = -(-(SIZE + 1) // PARTS)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, PARTS * width), np.int64)
        for batch in batches:
            for part in slices(batch):
                for at, y in zip(features(part.column("text")), part.column("quality").to_pylist(), strict=True):
                    total[y, at] += 1
                    total[y, SIZE] += 1
        for y in (0, 1):
            if total[y, SIZE]:
                sums = pa.array(list(total[y].reshape(PARTS, width)), pa.list_(pa.int64()))
                yield pa.record_batch([pa.array([y] * PARTS, pa.int32()), pa.array(range(PARTS), pa.int32()), sums], names=["quality", "part", "n"])

    def add(key, found):
        out = found.iloc[:1].copy()
        out.at[out.index[0], "n"] = np.sum(np.stack(found["n"].to_numpy()), axis=0)
        return out

    ddl = "quality int, part int, n array<bigint>"
    out = np.zeros((2, PARTS * width), np.int64)
    for r in rows.mapInArrow(count, ddl).groupBy("quality", "part").applyInPandas(add, ddl).collect():
        out[r["quality"], r["part"] * width : (r["part"] + 1) * width] = r["n"]
    return out[:, : SIZE + 1]


def log_ratio(counts: np.ndarray) -> np.ndarray:
    smooth = counts[:, :SIZE] + 1.0
    share = smooth / smooth.sum(1, keepdims=True)
    return np.log(share[1] / share[0])


def dual_descent(rows: list[np.ndarray], labels: np.ndarray, ratio: np.ndarray, rounds: int = ROUNDS, cost: float = COST, seed: int = 5):
    """Weights (already times the ratio) and bias of the hinge-loss model; each class gets an equal total cost."""
    values = [ratio[at] / max(1e-12, np.sqrt(np.square(ratio[at]).sum())) for at in rows]
    y = labels * 2.0 - 1
    share = np.where(y > 0, 0.5 / max(1e-12, (y > 0).mean()), 0.5 / max(1e-12, (y < 0).mean()))
    caps, alpha = cost * share, np.zeros(len(rows))
    norms = np.array([float(v @ v) + 1 for v in values])
    w, bias, rng = np.zeros(SIZE), 0.0, np.random.default_rng(seed)
    for _ in range(rounds):
        for i in rng.permutation(len(rows)):
            gradient = y[i] * (float(w[rows[i]] @ values[i]) + bias) - 1
            new = min(max(alpha[i] - gradient / norms[i], 0.0), caps[i])
            if new != alpha[i]:
                change = (new - alpha[i]) * y[i]
                w[rows[i]] += change * values[i]
                bias += change
                alpha[i] = new
    return w * ratio, bias


def sigmoid(margins: np.ndarray, labels: np.ndarray) -> tuple[float, float]:
    """Slope and level by Newton's method on the smoothed log loss."""
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    aim = np.where(labels == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    x, at = np.stack([margins, np.ones(len(margins))], 1), np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ at, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2), x.T @ (p - aim) + 1e-3 * (at - [1, 0]))
        at = at - step
        if np.abs(step).max() < 1e-9:
            break
    return max(1e-3, float(at[0])), float(at[1])


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Learns from rows outside the held-out fifth. Texts meet their labels once for the counts; the sample is
    cut by a hash of the id before its join."""
    learning = held_fold("doc_id", 5) != 0
    known = labels.where(F.col("quality").isin(0, 1)).select(F.col("doc_id").cast("long"), F.col("quality").cast("int")).where(learning)
    texts = docs.select(F.col("doc_id").cast("long"), "text").where(learning)
    counts = class_counts(texts.join(small(known, LABELS), "doc_id").select("text", "quality"))
    n0, n1 = counts[:, SIZE]
    if not n0 or not n1:
        p = (n1 / (n0 + n1)) if n0 + n1 else 0.5
        return Model(np.zeros(SIZE), np.zeros(SIZE), 0.0, 1.0, float(np.log((p + 1e-6) / (1 - p + 1e-6))))
    cut = int(min(1.0, sample / (n0 + n1)) * (1 << 32))
    chosen = F.crc32(F.concat(F.lit("fit:"), F.col("doc_id").cast("string")).cast("binary")) < cut
    few = texts.where(chosen).join(known.where(chosen), "doc_id").orderBy("doc_id", "text", "quality").limit(2 * sample)

    def code(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        found = [at.tobytes() for at in features(batch.column("text"))]
        yield pa.record_batch([batch.column("quality"), pa.array(found, pa.binary())], names=["quality", "at"])

    got = arrow_map(few, code, "quality int, at binary").collect()
    rows, y = [np.frombuffer(r["at"], np.int32) for r in got], np.array([r["quality"] for r in got])
    ratio = log_ratio(counts)
    held = np.arange(len(rows)) % 5 == 0
    if len(set(y[~held].tolist())) < 2 or len(set(y[held].tolist())) < 2:
        held[:] = True
        weights, bias = dual_descent(rows, y, ratio)
    else:
        weights, bias = dual_descent([r for r, h in zip(rows, held, strict=True) if not h], y[~held], ratio)
    model = Model(weights, ratio, bias, 1.0, 0.0)
    model.slope, model.level = sigmoid(np.array([model.margin(r) for r, h in zip(rows, held, strict=True) if h]), y[held])
    return model


def predict(docs: DataFrame, model: Model, cut: float = CUT) -> DataFrame:
    """doc_id, held_out, score and predicted of every document."""
    rows = docs.select(F.col("doc_id").cast("long"), "text", (held_fold("doc_id", 5) == 0).alias("held_out"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        score = [shared.value.score(at) for at in features(batch.column("text"))]
        yield rows_out(_FIELDS, doc_id=batch.column("doc_id"), held_out=batch.column("held_out"), score=score, predicted=[int(s >= cut) for s in score])

    return arrow_map(rows, run, DDL)


def op6_naive_bayes_svm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return predict(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
