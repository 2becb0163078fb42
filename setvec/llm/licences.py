"""License scans by a positional index of rare words.

Templates are passages of licences: short names, and sentences of their texts. Document counts of the licence words over
the whole corpus give inverse document frequencies, and every passage is indexed by its rarest words (one if the whole
passage is mandatory, else up to ``ANCHORS``). A file's words are looked up among these rare words alone; each place of
one proposes the start of its passages by relative position. At a proposed start the passage's other words are compared
from there on; it stands if words with at least ``SHARE`` of its weight are in their places and all its mandatory key
phrases are there word for word. A label counts when a passage of it that has key phrases stands; passages without them
only raise the score.

Words are runs of digits, letters and characters outside ASCII, after A-Z is lower-cased. A null or empty text has no
words, no labels and score 0. Places are counted for every passage, overlaps and repeats included. Repeated rows stay, an
empty table gives no rows, and other columns are ignored. A long text is cut into pieces for the look-up, its places
counted on.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, documents, rows_out, text_bytes

ANCHORS, SHARE = 3, 0.6

# Names of licences, each mandatory as a whole, with their labels. The first four are the base.
NAMES = (
    ("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"),
    ("gnu lesser general public license", "lgpl"), ("gnu affero general public license", "agpl"), ("mozilla public license", "mpl"),
    ("bsd license", "bsd"), ("isc license", "isc"), ("eclipse public license", "epl"), ("creative commons attribution", "cc-by"),
    ("cc0", "cc0"), ("creative commons zero", "cc0"), ("boost software license", "bsl"), ("unlicense", "unlicense"),
    ("all rights reserved", "reserved"),
)
N_BASE = 4

# Passages of licence texts, their labels, and the key phrases that must stand in them.
TEXTS = (
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the "
     "software to deal in the software without restriction including without limitation the rights to use copy modify merge publish "
     "distribute sublicense and or sell copies of the software", "mit", ("permission is hereby granted free of charge", "to deal in the software without restriction")),
    ("the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "mit", ()),
    ("the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of "
     "merchantability fitness for a particular purpose and noninfringement", "mit", ()),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions "
     "are met", "bsd", ("redistribution and use in source and binary forms",)),
    ("redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the "
     "documentation and or other materials provided with the distribution", "bsd", ()),
    ("neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from "
     "this software without specific prior written permission", "bsd-3", ("may be used to endorse or promote products",)),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that "
     "the above copyright notice and this permission notice appear in all copies", "isc", ("for any purpose with or without fee is hereby granted",)),
    ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "apache",
     ("apache license version 2 0", "except in compliance with the license")),
    ("unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis "
     "without warranties or conditions of any kind either express or implied", "apache", ()),
    ("it under the terms of the gnu general public license as published by the free software foundation either version", "gpl",
     ("gnu general public license as published by the free software foundation",)),
    ("it under the terms of the gnu lesser general public license as published by the free software foundation either version", "lgpl",
     ("gnu lesser general public license as published by the free software foundation",)),
    ("it under the terms of the gnu affero general public license as published by the free software foundation either version", "agpl",
     ("gnu affero general public license as published by the free software foundation",)),
    ("in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a "
     "particular purpose", "gpl", ()),
    ("this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this "
     "file you can obtain one at", "mpl", ("subject to the terms of the mozilla public license",)),
    ("this is free and unencumbered software released into the public domain", "unlicense", ("free and unencumbered software",)),
    ("the origin of this software must not be misrepresented you must not claim that you wrote the original software", "zlib",
     ("origin of this software must not be misrepresented",)),
    ("permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying "
     "documentation covered by this license", "bsl", ("any person or organization obtaining a copy",)),
    ("this work is licensed under a creative commons attribution 4 0 international license", "cc-by", ("creative commons attribution",)),
    ("to the extent possible under law the person who associated cc0 with this work has waived all copyright and related or neighboring "
     "rights to this work", "cc0", ("waived all copyright and related or neighboring rights",)),
    ("the accompanying materials are made available under the terms of the eclipse public license", "epl", ("eclipse public license",)),
)


@dataclass(frozen=True)
class Passage:
    """``keys``: where each mandatory phrase begins and ends, by place in ``words``. ``whole``: all words are mandatory."""

    label: str
    words: tuple[bytes, ...]
    keys: tuple[tuple[int, int], ...]
    whole: bool


def _place(words: tuple[bytes, ...], phrase: tuple[bytes, ...]) -> tuple[int, int]:
    at = next(i for i in range(len(words)) if words[i : i + len(phrase)] == phrase)
    return at, at + len(phrase)


def _passages() -> list[Passage]:
    cut = lambda x: tuple(x.encode().split())
    names = [Passage(label, cut(x), ((0, len(cut(x))),), True) for x, label in NAMES]
    return names + [Passage(label, cut(x), tuple(_place(cut(x), cut(k)) for k in keys), False) for x, label, keys in TEXTS]


PASSAGES = _passages()
VOCABULARY = frozenset(w for p in PASSAGES for w in p.words)
_WORD = np.ones(256, bool)
_WORD[[*range(0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]] = False
#: Lower-cases A-Z and makes a space of every byte that isn't in a word.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if _WORD[b] else 32 for b in range(256))
#: Bytes of a text whose words are listed at once.
PIECE = 1 << 20

_FIELDS = pa.schema(
    [(n, pa.int64()) for n in ("doc_id", "n_words", "n_base", "first_word", "last_word")]
    + [("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64())]
    + [("starts", pa.list_(pa.int64())), ("passages", pa.list_(pa.int32()))]
)
DDL = (
    "doc_id bigint, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, "
    "labels string, score double, starts array<bigint>, passages array<int>"
)


def _folded(batch: pa.RecordBatch) -> Iterator[bytes]:
    raw, starts, lengths = text_bytes(batch.column("text"))
    data = raw.tobytes().translate(_FOLD)
    for a, n in zip(starts.tolist(), lengths.tolist(), strict=True):
        yield data[a : a + n]


def _pieces(text: bytes, most: int | None = None) -> Iterator[list[bytes]]:
    """The words of a folded text, piece by piece."""
    most, a = most or PIECE, 0
    while len(text) - a > most and (cut := text.find(b" ", a + most)) >= 0:
        yield text[a:cut].split()
        a = cut
    yield text[a:].split()


def document_counts(docs: DataFrame) -> dict[bytes, int]:
    """In how many documents each licence word stands, and under '' the number of documents. One short row for each
    word and task is shuffled."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = dict.fromkeys([*sorted(VOCABULARY), b""], 0)
        for batch in batches:
            for text in _folded(batch):
                for w in frozenset().union(*map(VOCABULARY.intersection, _pieces(text))):
                    total[w] += 1
                total[b""] += 1
        yield pa.record_batch([pa.array([w.decode() for w in total]), pa.array(list(total.values()), pa.int64())], names=["word", "n"])

    rows = docs.select("text").mapInArrow(count, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))
    return {r["word"].encode(): r["n"] for r in rows.collect()}


def idf(counts: dict[bytes, int]) -> dict[bytes, float]:
    n = counts.get(b"", 0)
    return {w: math.log((n + 1) / (counts.get(w, 0) + 1)) + 1e-9 for w in VOCABULARY}


class Index:
    """Postings of the passages' rarest words: for each such word the passages and places it proposes."""

    def __init__(self, weights: dict[bytes, float]):
        self.mass = [sum(weights[w] for w in p.words) for p in PASSAGES]
        self.weights = [[weights[w] for w in p.words] for p in PASSAGES]
        self.postings: dict[bytes, list[tuple[int, int]]] = {}
        for i, p in enumerate(PASSAGES):
            rarest = sorted(range(len(p.words)), key=lambda k, p=p: (-weights[p.words[k]], k))
            for k in rarest[: 1 if p.whole else ANCHORS]:
                self.postings.setdefault(p.words[k], []).append((i, k))
        self.rare = frozenset(self.postings)
        self.whole: dict[str, float] = {}
        for i, p in enumerate(PASSAGES):
            self.whole[p.label] = self.whole.get(p.label, 0.0) + self.mass[i]

    def places(self, text: bytes) -> tuple[int, list[tuple[int, int, float]]]:
        """The number of words, and (start, passage, share of its weight that is in place) of all that stand."""
        n, hits = 0, []
        for words in _pieces(text):
            if not self.rare.isdisjoint(words):
                hits += [(n + i, w) for i, w in enumerate(words) if w in self.rare]
            n += len(words)
        if not hits:
            return n, []
        flags = np.concatenate([[False], np.frombuffer(text, np.uint8) != 32, [False]])
        edges = np.flatnonzero(flags[1:] != flags[:-1])
        begin, end = edges[::2], edges[1::2]
        found = []
        for start, i in sorted({(at - k, i) for at, w in hits for i, k in self.postings[w]}):
            share = self._stands(text, begin, end, start, i)
            if share:
                found.append((start, i, share))
        return n, found

    def _stands(self, text: bytes, begin: np.ndarray, end: np.ndarray, start: int, i: int) -> float:
        """The share of a passage's weight that is in place, or 0 where it doesn't stand. A passage that begins before
        the text or ends after it has no words in place there."""
        p = PASSAGES[i]
        same = [0 <= start + k < len(begin) and text[begin[start + k] : end[start + k]] == w for k, w in enumerate(p.words)]
        if not all(all(same[a:b]) for a, b in p.keys):
            return 0.0
        share = sum(x for x, s in zip(self.weights[i], same, strict=True) if s) / self.mass[i]
        return share if share >= SHARE else 0.0

    def report(self, found: list[tuple[int, int, float]]) -> tuple[str, str, float]:
        """Base labels, all labels, and the best label's share of the weight of its passages."""
        best: dict[int, float] = {}
        for _, i, share in found:
            best[i] = max(best.get(i, 0.0), share)
        base = {PASSAGES[i].label for i in best if i < N_BASE}
        labels = {PASSAGES[i].label for i in best if PASSAGES[i].keys}
        got = {x: sum(s * self.mass[i] for i, s in best.items() if PASSAGES[i].label == x) / self.whole[x] for x in labels}
        return ",".join(sorted(base)), ",".join(sorted(labels)), min(1.0, 0.5 + 0.5 * max(got.values())) if got else 0.0


def scan(docs: DataFrame, counts: dict[bytes, int] | None = None) -> DataFrame:
    """Words, places and labels of each document. ``counts``: from ``document_counts``, which else runs first."""
    index = Index(idf(document_counts(docs) if counts is None else counts))

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        rows = []
        for text in _folded(batch):
            n, found = index.places(text)
            base = [s for s, i, _ in found if i < N_BASE]
            ends = (min(base), max(base)) if base else (None, None)
            rows.append((n, len(base), *ends, *index.report(found), [s for s, _, _ in found], [i for _, i, _ in found]))
        yield rows_out(_FIELDS, doc_id=batch.column("doc_id"), **dict(zip(_FIELDS.names[1:], zip(*rows, strict=True), strict=True)))

    return arrow_map(docs.select(F.col("doc_id").cast("long"), "text"), run, DDL)


def op8_rare_token_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(documents(spark, sf_dir)).drop("starts", "passages")
