"""Token ids of whole texts by the lower-casing word BPE, with pieces kept in a bounded table.

The tokenizer's own pattern cuts a text into pieces that are coded one by one, so equal pieces have equal ids. Texts
of plain letters, digits, marks and white space are cut here by the same pattern, from the kinds of their bytes; Arrow
numbers the different pieces and looks them up, and a text's ids are gathered from its pieces' ids. A new piece is coded
by the tokenizer's own model and kept. Any other text, and every text under a vocabulary file whose rules of lowering and
cutting are not those, is coded whole by the library.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

NAME = "word_bpe_49k.json"
END_ID = 1
#: Bytes of the pieces that are kept; where new ones would pass it, only those of the present texts stay.
KEPT_BYTES = 8 << 20
#: Characters of text cut at once; a longer text is first divided at white space, which no piece holds.
AT_ONCE = 2 << 20

# The characters that normalising only lower-cases, and endings that stay with an apostrophe.
_PLAIN = re.compile(r"[\t\n\r\x20-\x7e\xc0-\xd6\xd8-\xf6\xf8-\xff]*")
_SHORT_ENDINGS, _LONG_ENDINGS = ("s", "t", "m", "d"), ("re", "ve", "ll")

_SPACE = re.compile(r"[\t\n\r ]")
_GAP, _LETTER, _DIGIT, _MARK = range(4)
#: Kind of each byte of a lower-cased plain text in UTF-8; its bytes from 128 on belong to letters, 0 ends a text.
_KINDS = np.full(256, _MARK, np.uint8)
_KINDS[[0, 9, 10, 13, 32]] = _GAP
_KINDS[ord("a") : ord("z") + 1] = _KINDS[128:] = _LETTER
_KINDS[ord("0") : ord("9") + 1] = _DIGIT

#: Bytes that the byte-level alphabet shows as other characters: those from 256 on, in order.
_HIDDEN = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)]
_SHOWN = {b: 256 + i for i, b in enumerate(_HIDDEN)}


def _begins(raw: np.ndarray, kinds: np.ndarray) -> np.ndarray:
    """Where the pieces of lower-cased texts begin: at each digit, each run of letters and each run of marks. A lone
    apostrophe takes an ending of _SHORT_ENDINGS or _LONG_ENDINGS with it, and what follows begins anew."""
    fresh = kinds == _DIGIT
    fresh[0] = True
    fresh[1:] |= kinds[1:] != kinds[:-1]
    at = np.flatnonzero((raw == ord("'")) & fresh)
    at = at[kinds[at + 1] == _LETTER]
    first, second = raw[at + 1], raw[at + 2]
    short = at[np.isin(first, [ord(x) for x in _SHORT_ENDINGS])]
    long = at[np.any([(first == ord(x[0])) & (second == ord(x[1])) for x in _LONG_ENDINGS], axis=0)]
    fresh[np.concatenate([short, long]) + 1] = False
    fresh[np.concatenate([short + 2, long + 3])] = True
    return np.flatnonzero(fresh & (kinds != _GAP))


def _parts(text: str) -> Iterator[str]:
    """A text cut at white space into parts of AT_ONCE characters and up to the next white space."""
    a = 0
    while len(text) - a > AT_ONCE and (gap := _SPACE.search(text, a + AT_ONCE)):
        yield text[a : gap.start()]
        a = gap.start()
    yield text[a:]


def _default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(NAME)


@lru_cache(maxsize=4)
def _rules(path: str) -> str:
    """What a vocabulary file says of normalising, cutting and the form of its pieces, as one text."""
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    model = {k: v for k, v in told.get("model", {}).items() if k not in ("vocab", "merges")}
    return json.dumps([told.get("normalizer"), told.get("pre_tokenizer"), told.get("added_tokens"), model], sort_keys=True)


class Coder:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.size = max(self.tokenizer.get_vocab().values()) + 1
        self.model = self.tokenizer.model
        self.cuts = _rules(path) == _rules(_default_path())
        self._forget()

    def _forget(self) -> None:
        """``ids[ends[i] : ends[i + 1]]`` are the ids of the i-th known piece."""
        self.known, self.ids, self.ends = pa.array([], pa.large_string()), np.zeros(0, "<u4"), np.zeros(1, np.int64)

    def _piece(self, piece: str) -> list[int]:
        shown = piece if piece.isascii() else piece.encode().decode("latin-1").translate(_SHOWN)
        return [t.id for t in self.model.tokenize(shown)]

    def _places(self, pieces: pa.LargeStringArray) -> np.ndarray:
        """Places of different pieces in the table; new ones are coded and added."""
        found = pc.index_in(pieces, self.known)
        new = pieces.filter(found.is_null())
        if self.known.nbytes + new.nbytes > KEPT_BYTES and len(self.known):
            self._forget()
            return self._places(pieces)
        first = len(self.known)
        coded = [self._piece(x) for x in new.to_pylist()]
        self.known = pa.concat_arrays([self.known, new])
        self.ids = np.concatenate([self.ids, np.fromiter(chain.from_iterable(coded), "<u4")])
        self.ends = np.concatenate([self.ends, self.ends[-1] + np.cumsum(np.fromiter(map(len, coded), np.int64, len(coded)))])
        at = found.fill_null(-1).to_numpy().astype(np.int64)
        at[at < 0] = first + np.arange(len(new))
        return at

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def plain(self, texts: list[str]) -> list[bytes]:
        """Ids of texts in the characters of _PLAIN."""
        raw = np.frombuffer("\0".join([*texts, ""]).lower().encode(), np.uint8)
        if not len(raw):
            return []
        kinds = _KINDS[raw]
        begin, solid = _begins(raw, kinds), kinds != _GAP
        # Without white space, pieces touch, and each ends where the next begins.
        offsets = np.append((np.cumsum(solid) - 1)[begin], np.count_nonzero(solid))
        named = pa.LargeStringArray.from_buffers(len(begin), pa.py_buffer(offsets), pa.py_buffer(raw[solid])).dictionary_encode()
        place = self._places(named.dictionary)[named.indices.to_numpy()]
        starts, n = self.ends[place], np.diff(self.ends)[place]
        ends = np.append(0, np.cumsum(n))
        out = self.ids[np.arange(ends[-1]) + np.repeat(starts - ends[:-1], n)]
        edges = [0, *ends[np.searchsorted(begin, np.flatnonzero(raw == 0))].tolist()]
        return [out[a:b].tobytes() for a, b in zip(edges, edges[1:], strict=False)]

    def _coded(self, texts: list[str]) -> Iterator[bytes]:
        held, n = [], 0
        for text in texts:
            if held and n + len(text) > AT_ONCE:
                yield from self.plain(held)
                held, n = [], 0
            if len(text) > AT_ONCE:
                yield b"".join(self.plain([x])[0] for x in _parts(text))
            else:
                held.append(text)
                n += len(text)
        yield from self.plain(held)

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text, as little-endian unsigned 32-bit integers."""
        is_plain = [self.cuts and _PLAIN.fullmatch(x) is not None and "<|" not in x for x in texts]
        coded = self._coded([x for x, p in zip(texts, is_plain, strict=True) if p])
        return [next(coded) if p else self.whole(x) for x, p in zip(texts, is_plain, strict=True)]


@lru_cache(maxsize=2)
def _coder(path: str) -> Coder:
    return Coder(path)


def coder(path: str | None = None) -> Coder:
    """One coder for each process and vocabulary file; the default file is found on the machine that runs it."""
    return _coder(path or _default_path())
