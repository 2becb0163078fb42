"""Word and shingle hashes of whole slices of texts, by array arithmetic on their bytes.

Words are runs of bytes other than ASCII white space, after lower-casing; a shingle is five consecutive words. A text of
one to four words is one shingle of all its words; a text without words has none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from setvec.llm.common import text_bytes, word_spans

WORDS = 5
_BASE = 0x9E3779B97F4A7C15
_UNBASE = pow(_BASE, -1, 1 << 64)
_BYTE = np.random.default_rng(7).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_WORD = np.ones(256, bool)
_WORD[[9, 10, 11, 12, 13, 32]] = False
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    if len(_POWERS.get(base, ())) < n:
        steps = np.full(n, base, np.uint64)
        steps[0] = 1
        _POWERS[base] = np.multiply.accumulate(steps)
    return _POWERS[base][:n]


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(raw: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes: differences of one running sum, moved to the same power."""
    total = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(_BYTE[raw] * _powers(_BASE, max(1, len(raw)))[: len(raw)], out=total[1:])
    return mixed((total[end] - total[begin]) * _powers(_UNBASE, len(raw) + 1)[begin] + (end - begin).astype(np.uint64))


def word_hashes(column: pa.Array, lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Hash and document of every word of a string column."""
    raw, starts, lengths = text_bytes(pc.utf8_lower(column) if lower else column)
    begin, end, owner = word_spans(raw, starts, lengths, _WORD)
    return span_hashes(raw, begin, end), owner


def shingle_sets(column: pa.Array) -> Iterator[np.ndarray]:
    """For each row the sorted distinct hashes of its shingles."""
    words, owner = word_hashes(column)
    n = len(words)
    window = np.zeros(max(0, n - WORDS + 1), np.uint64)
    for k in range(WORDS):
        window *= np.uint64(_BASE)
        window += words[k : k + len(window)]
    window = mixed(window)
    edges = np.searchsorted(owner, np.arange(len(column) + 1))
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        if b - a >= WORDS:
            yield np.unique(window[a : b - WORDS + 1])
        elif b > a:
            short = np.full(1, b - a, np.uint64)
            for k in range(a, b):
                short = mixed(short * np.uint64(3) + words[k : k + 1])
            yield short
        else:
            yield np.zeros(0, np.uint64)
