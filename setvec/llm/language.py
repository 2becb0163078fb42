"""Language ID by a mixture over languages, fitted to each document by expectation-maximisation.

Training counts hashed letter n-grams (one to three letters, with word edges) per language over all learning documents.
A word's likelihood under a language is the product over its n-grams. A document is a mixture of languages over its
words. The set of languages grows from the best single one: another joins while the penalised log-likelihood rises,
with a penalty of ``PENALTY`` times the log of the number of words. Where even the best choice for every word alone
couldn't pay the penalty, the single language stands and no expectation-maximisation runs.

``und`` with score 0: a null text or one without a letter. Ties go to the language first by code point. Repeated rows
stay, an empty table gives no rows, and other columns are ignored (``accepted`` keeps them). Without any learning
document every text is ``und``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, bounded_batches, documents, held_fold, rows_out, slices, text_bytes

BITS, SMOOTH, PENALTY, ROUNDS = 16, 0.5, 4.0, 12
#: Chance of a word's end after a letter, where letters are drawn one by one.
EDGE = 0.2
#: A document is rejected when letters without a language are likelier than its mixture by this much a word (natural log).
SURE = 4.0
PARTS = 64
#: Bytes of text at once: each byte of a word becomes several numbers for each language.
SLICE = 1 << 20
UNKNOWN = "und"
_FIELDS = pa.schema(
    [("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64())]
    + [("langs", pa.list_(pa.string())), ("shares", pa.list_(pa.float64()))]
)
DDL = "doc_id bigint, held_out boolean, lang_pred string, score double, langs array<string>, shares array<double>"

# ASCII letters are marked; so is every byte outside ASCII, which letters of most languages hold.
_LETTER = np.zeros(256, bool)
_LETTER[[*range(97, 123), *range(128, 256)]] = True
_MIX = np.uint32(0x9E3779B1)


def bucket(v: np.ndarray, order: int) -> np.ndarray:
    """Buckets of n-grams of one order, given as their bytes in one number."""
    return (v * _MIX ^ np.uint32(order * 0x85EBCA6B & 0xFFFFFFFF)) * np.uint32(0xC2B2AE35) >> np.uint32(32 - BITS)


def grams(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashed n-grams of a slice of texts: (buckets of each order as rows, starts of words among the letters, the
    document of each word, whether a document has a letter, each letter's byte with the two before it). Bytes of words
    stand one after another, each word with an edge byte before it."""
    has = pc.fill_null(pc.match_substring_regex(column, r"\p{L}"), False).to_numpy(zero_copy_only=False)
    raw, starts, lengths = text_bytes(pc.utf8_lower(column))
    inside = np.zeros(len(raw) + 1, bool)
    inside[1:] = _LETTER[raw]
    edge = starts[(starts < len(raw)) & (lengths > 0)]
    first = inside[1:] & ~inside[:-1]
    first[edge] = inside[1:][edge]
    at = np.flatnonzero(inside[1:])
    begins = first[at]
    words = np.flatnonzero(begins)
    filled = np.flatnonzero(lengths > 0)
    owner = filled[np.searchsorted(starts[filled], at[words], side="right") - 1] if len(words) else np.zeros(0, np.int64)
    x = raw[at].astype(np.uint32)
    since = np.arange(len(at)) - np.repeat(words, np.diff([*words, len(at)])) if len(words) else np.zeros(0, np.int64)
    one = np.concatenate([[0], x[:-1]]).astype(np.uint32)[: len(x)]
    two = np.concatenate([[0, 0], x[:-2]]).astype(np.uint32)[: len(x)]
    one[since < 1], two[since < 2], two[since < 1] = 1, 1, 2
    wide = x | (one << np.uint32(8))
    most = wide | (two << np.uint32(16))
    codes = [bucket(v, n) for n, v in ((1, x), (2, wide), (3, most))]
    return np.stack(codes) if len(x) else np.zeros((3, 0), np.uint32), words, owner, has, np.stack([x, one, two])


class Model:
    """Log-probabilities of buckets (rows) in each language (columns)."""

    def __init__(self, langs: list[str], counts: np.ndarray):
        self.langs = langs
        smooth = counts.T.astype(np.float64) + SMOOTH
        self.logs = np.log(smooth / smooth.sum(0, keepdims=True)).astype(np.float32) if langs else np.zeros((1 << BITS, 0), np.float32)
        # Letters drawn one by one, with the frequencies of all languages together: no language at all.
        alone = (counts.sum(0) + SMOOTH)[bucket(np.arange(256, dtype=np.uint32), 1)]
        alone = np.where(_LETTER, alone, 0) / alone[_LETTER].sum()
        alone[1], alone[2] = EDGE, 1
        self.alone = np.log(np.maximum(alone, 1e-12))

    def words(self, column: pa.Array, noise: bool = False) -> tuple[np.ndarray, ...]:
        """Log-likelihood of each word in each language, each word's document, and whether a document has a letter; with
        ``noise`` also each word's without any language: letters drawn one by one, or every bucket alike."""
        codes, words, owner, has, letters = grams(column)
        if not len(words):
            return (np.zeros((0, len(self.langs))), owner, has, *([np.zeros(0)] if noise else []))
        total = self.logs[codes[0]]
        total += self.logs[codes[1]]
        total += self.logs[codes[2]]
        out = np.add.reduceat(total, words, axis=0).astype(np.float64) / 3, owner, has
        if not noise:
            return out
        # The three orders share one table, a third of it each; the shorter the n-gram, the fewer letters it holds.
        x, one, two = self.alone[letters]
        drawn = np.add.reduceat(x + 2 / 3 * one + 1 / 3 * two - np.log(3), words)
        return *out, np.maximum(drawn, -BITS * np.log(2) * np.diff([*words, len(x)]))


def em(ll: np.ndarray, owner: np.ndarray, n: int, allowed: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
    """Shares of the allowed languages (documents by languages) and the log-likelihood, all documents at once.

    Words lie by document. Shares start equal over the allowed languages.
    """
    share = allowed / np.maximum(1, allowed.sum(1, keepdims=True))
    count = np.bincount(owner, minlength=n).astype(np.float64)
    firsts = np.flatnonzero(np.diff(owner, prepend=-1))
    docs = owner[firsts]
    peak = ll.max(1, keepdims=True)
    like = np.exp(ll - peak)
    for _ in range(rounds):
        mass = like * share[owner]
        mass /= np.maximum(mass.sum(1, keepdims=True), 1e-300)
        new = np.zeros_like(share)
        new[docs] = np.add.reduceat(mass, firsts, axis=0)
        share = new / np.maximum(count, 1)[:, None]
    value = np.log(np.maximum((like * share[owner]).sum(1), 1e-300)) + peak[:, 0]
    total = np.zeros(n)
    total[docs] = np.add.reduceat(value, firsts)
    return share, total


def pair(ll: np.ndarray, owner: np.ndarray, best: np.ndarray, some: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For documents ``some`` the second language that most raises the likelihood, the rise, and its share.

    With two languages only the ratio of a word's likelihoods counts, so a round is a few operations on one number a word.
    """
    here = np.zeros(len(best), bool)
    here[some] = True
    at = np.flatnonzero(here[owner])
    number = np.cumsum(here) - 1
    own = number[owner[at]]
    firsts = np.flatnonzero(np.diff(own, prepend=-1))
    count = np.diff([*firsts, len(own)])
    base = ll[at, best[owner[at]]]
    top, lang, part = np.full(len(some), -np.inf), np.zeros(len(some), np.int64), np.zeros(len(some))
    for other in range(ll.shape[1]):
        ratio = np.exp(np.minimum(ll[at, other] - base, 60.0))
        p = np.full(len(some), 0.5)
        for _ in range(rounds):
            mass = ratio * p[own]
            p = np.add.reduceat(mass / (mass + (1 - p)[own]), firsts) / count
        rise = np.add.reduceat(np.log1p(p[own] * (ratio - 1)), firsts)
        better = (best[some] != other) & (rise > top)
        top[better], lang[better], part[better] = rise[better], other, p[better]
    return top, lang, part


def mixture(ll: np.ndarray, owner: np.ndarray, n: int, penalty: float = PENALTY) -> np.ndarray:
    """Each document's language shares after the penalised choice of its set of languages."""
    k = ll.shape[1]
    if not len(owner) or not k:
        return np.zeros((n, k))
    firsts = np.flatnonzero(np.diff(owner, prepend=-1))
    docs = owner[firsts]
    single, bound = np.full((n, k), -np.inf), np.zeros(n)
    single[docs] = np.add.reduceat(ll, firsts, axis=0)
    bound[docs] = np.add.reduceat(ll.max(1), firsts)
    cost = penalty * np.log(np.maximum(2, np.bincount(owner, minlength=n)))
    best = single.argmax(1)
    rows = np.arange(n)
    share = np.zeros((n, k))
    share[docs, best[docs]] = 1
    value = single[rows, best]
    open_docs = np.zeros(n, bool)
    open_docs[docs] = bound[docs] - value[docs] > cost[docs]
    if k > 1 and open_docs.any():
        some = np.flatnonzero(open_docs)
        gain, second, part = pair(ll, owner, best, some)
        won, second, part = (x[gain > cost[some]] for x in (some, second, part))
        value[won] += gain[gain > cost[some]]
        share[won, best[won]], share[won, second] = 1 - part, part
        open_docs[:] = False
        open_docs[won] = (bound[won] - value[won] > cost[won]) & (k > 2)
    allowed = share > 0
    while open_docs.any():
        some = np.flatnonzero(open_docs)
        renumber = np.full(n, -1)
        renumber[some] = np.arange(len(some))
        here = open_docs[owner]
        sub, sub_owner = ll[here], renumber[owner[here]]
        top, top_share, top_lang = np.full(len(some), -np.inf), np.zeros((len(some), k)), np.zeros(len(some), np.int64)
        for lang in range(k):
            if allowed[some, lang].all():
                continue
            grown = allowed[some].copy()
            fresh = ~grown[:, lang]
            grown[:, lang] = True
            got, total = em(sub, sub_owner, len(some), grown)
            better = fresh & (total > top)
            top[better], top_lang[better] = total[better], lang
            top_share[better] = got[better]
        gain = top - value[some] > cost[some]
        won = some[gain]
        share[won], value[won] = top_share[gain], top[gain]
        allowed[won, top_lang[gain]] = True
        open_docs[:] = False
        open_docs[won] = (bound[won] - value[won] > cost[won]) & (allowed[won].sum(1) < k)
    return share


def learn(docs: DataFrame, languages: int = 256) -> Model:
    """Counts over all rows with a text and a lang. Each task sums its own counts and emits them in PARTS slices per
    language, so that a language with most rows is no larger group than another. ``languages`` bounds the table that
    reaches the driver (that many times 2^BITS counts); more distinct values raise an error."""
    spark = docs.sparkSession
    bounded_batches(spark)
    width = (1 << BITS) // PARTS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for part in slices(batch, most=SLICE):
                codes, words, owner, *_ = grams(part.column("text"))
                if not len(words):
                    continue
                names = part.column("lang").dictionary_encode()
                at = names.indices.to_numpy()
                letters = np.repeat(at[owner], np.diff([*words, codes.shape[1]]))
                for i, name in enumerate(names.dictionary.to_pylist()):
                    sums = np.bincount(codes[:, letters == i].ravel(), minlength=1 << BITS)
                    total[name] = total[name] + sums if name in total else sums
        for name, sums in total.items():
            yield pa.record_batch(
                [pa.array([name] * PARTS), pa.array(range(PARTS), pa.int32()), pa.array(list(sums.reshape(PARTS, width)), pa.list_(pa.int64()))],
                names=["lang", "part", "n"],
            )

    def add(key, rows):
        out = rows.iloc[:1].copy()
        out.at[out.index[0], "n"] = np.sum(np.stack(rows["n"].to_numpy()), axis=0)
        return out

    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("text", F.col("lang").cast("string"))
    ddl = "lang string, part int, n array<bigint>"
    rows = known.mapInArrow(count, ddl).groupBy("lang", "part").applyInPandas(add, ddl).take(languages * PARTS + 1)
    if len(rows) > languages * PARTS:
        raise ValueError(f"more than {languages} languages; raise the bound")
    langs = sorted({r["lang"] for r in rows})
    counts = np.zeros((len(langs), 1 << BITS), np.int64)
    for r in rows:
        counts[langs.index(r["lang"]), r["part"] * width : (r["part"] + 1) * width] = r["n"]
    return Model(langs, counts)


def predict(docs: DataFrame, model: Model, held_out: F.Column | None = None) -> DataFrame:
    """lang_pred, its score (share in the mixture), and the whole mixture of each document."""
    held = F.lit(False) if held_out is None else held_out
    rows = docs.select(F.col("doc_id").cast("long"), "text", held.alias("held_out"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        m = shared.value
        ll, owner, has = m.words(batch.column("text"))
        share = mixture(ll, owner, batch.num_rows)
        known = has & (share.sum(1) > 0) if m.langs else np.zeros(batch.num_rows, bool)
        best = share.argmax(1) if m.langs else np.zeros(batch.num_rows, np.int64)
        names = [m.langs[b] if k else UNKNOWN for b, k in zip(best, known, strict=True)]
        score = [float(min(1.0, share[i, b])) if known[i] else 0.0 for i, b in enumerate(best)]
        sets = [[j for j in np.argsort(-s, kind="stable") if s[j] > 0] if k else [] for s, k in zip(share, known, strict=True)]
        yield rows_out(
            _FIELDS, doc_id=batch.column("doc_id"), held_out=batch.column("held_out"), lang_pred=names, score=score,
            langs=[[m.langs[j] for j in s] for s in sets], shares=[[float(share[i, j]) for j in s] for i, s in enumerate(sets)],
        )

    return arrow_map(rows, run, DDL, SLICE)


def trained(docs: DataFrame) -> Model:
    """Learns from documents whose crc32 of the id modulo 3 isn't 1."""
    return learn(docs.where(held_fold("doc_id", 3) != 1))


def told(ll: np.ndarray, noise: np.ndarray, owner: np.ndarray, share: np.ndarray, sure: float = SURE) -> np.ndarray:
    """Which documents a language explains: what no language makes may not beat the document's mixture by more than
    ``sure`` a word."""
    n = len(share)
    if not len(owner):
        return np.zeros(n, bool)
    value = ll.max(1) + np.log(np.maximum((np.exp(ll - ll.max(1, keepdims=True)) * share[owner]).sum(1), 1e-300))
    gain = np.bincount(owner, noise - value, n)
    count = np.bincount(owner, minlength=n)
    return (share.sum(1) > 0) & (gain <= sure * count)


def accepted(docs: DataFrame, model: Model) -> DataFrame:
    """The documents whose language could be told, with all their columns. Those without any letter go, and those that
    no mixture of learned languages explains (see ``told``). A null ``lang`` is filled with the
    language found, where the table has that column as text. Without any learning document none is told."""
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    fill = "lang" in docs.columns and dict(docs.dtypes)["lang"] == "string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, most=SLICE):
                ll, owner, has, noise = shared.value.words(part.column("text"), True)
                share = mixture(ll, owner, part.num_rows)
                keep = has & told(ll, noise, owner, share) if shared.value.langs else np.zeros(part.num_rows, bool)
                if fill and part.column("lang").null_count:
                    at, own = part.schema.get_field_index("lang"), part.column("lang")
                    found = pa.array([shared.value.langs[b] if k else None for b, k in zip(share.argmax(1), keep, strict=True)], own.type) if shared.value.langs else own
                    part = part.set_column(at, part.schema.field(at), pc.coalesce(own, found))
                yield part.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)


def op10_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    rows = predict(docs, trained(docs), held_fold("doc_id", 3) == 1)
    return rows.select("doc_id", "held_out", "lang_pred", "score", F.array_join("langs", ",").alias("langs"))
