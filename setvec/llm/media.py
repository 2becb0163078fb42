"""Media columns: WAV bytes, short-time Fourier transforms, and spectral-peak pair fingerprints.

A payload is stored as an 8-bit mono WAV file by the ``wave`` module and read back by it. The samples are cut into
Hann-windowed frames; in each frame and frequency band the strongest bin is a peak when its level is no lower than the
same band's in the frames before and after. Each peak is paired with the next few peaks in a target zone; a pair is
kept as a frame number (its time) and a code of both bins and the frames between them.

Null and empty texts give one block of spaces, hence one frame. A text of any length is handled in blocks of frames.
Equal texts give equal rows, repeated rows stay, an empty table gives no rows, and other columns are ignored.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setvec.llm.common import arrow_map, documents, rows_out, stored, texts_of

BLOCK, RATE, FRAME, HOP = 192, 8000, 192, 96
BANDS = ((2, 10), (10, 20), (20, 40), (40, 97))
FAN, ZONE, FRAMES_AT_ONCE = 3, 24, 4096

_WINDOW = np.hanning(FRAME)

MEDIA_FIELDS = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary())])
READ_FIELDS = pa.schema(
    [("doc_id", pa.int64())]
    + [(n, pa.int64()) for n in ("n_bytes", "payload_bytes")]
    + [("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64())]
    + [("media_sha256", pa.string()), ("feature", pa.string()), ("n_frames", pa.int64())]
    + [("times", pa.list_(pa.int32())), ("codes", pa.list_(pa.int32())), ("media", pa.binary())]
)
MEDIA_DDL = "doc_id bigint, n_bytes bigint, media binary"
READ_DDL = (
    "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, "
    "media_bytes bigint, media_sha256 string, feature string, n_frames bigint, times array<int>, codes array<int>, media binary"
)


def padded(raw: bytes) -> bytes:
    """Spaces are added up to a positive multiple of the block."""
    return raw + b" " * (max(1, -(-len(raw) // BLOCK)) * BLOCK - len(raw))


def to_wav(payload: bytes) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(payload)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as r:
        return r.readframes(r.getnframes())


def levels(samples: np.ndarray) -> np.ndarray:
    """Quantised power of each frame and frequency: half decibels above one unit, as integers."""
    if len(samples) < FRAME:
        samples = np.concatenate([samples, np.full(FRAME - len(samples), 128, np.uint8)])
    frames = np.lib.stride_tricks.sliding_window_view(samples, FRAME)[::HOP]
    out = np.empty((len(frames), FRAME // 2 + 1), np.int16)
    for a in range(0, len(frames), FRAMES_AT_ONCE):
        spectrum = np.fft.rfft((frames[a : a + FRAMES_AT_ONCE] - 128.0) * _WINDOW, axis=1)
        power = spectrum.real**2 + spectrum.imag**2
        out[a : a + FRAMES_AT_ONCE] = np.rint(20 * np.log10(power + 1))
    return out


def peaks(level: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frame and bin of each peak, by frame and then bin. A tie in a band goes to its lower bin."""
    times, bins = [], []
    for low, high in BANDS:
        part = level[:, low:high]
        best = part.argmax(1)
        top = part[np.arange(len(part)), best].astype(np.int32)
        before, after = np.concatenate([[-1], top[:-1]]), np.concatenate([top[1:], [-1]])
        t = np.flatnonzero((top > 0) & (top >= before) & (top > after))
        times.append(t)
        bins.append(best[t] + low)
    t, f = np.concatenate(times), np.concatenate(bins)
    order = np.lexsort((f, t))
    return t[order], f[order]


def pairs(t: np.ndarray, f: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Anchor times and codes: each peak with each of the next FAN peaks that lies 1 to ZONE frames later."""
    times, codes, rank = [], [], []
    for k in range(1, 1 + FAN + len(BANDS)):
        gap = t[k:] - t[:-k]
        keep = np.flatnonzero((gap >= 1) & (gap <= ZONE))
        times.append(t[keep])
        codes.append((f[keep].astype(np.int64) << 16) | (f[keep + k].astype(np.int64) << 8) | gap[keep])
        rank.append(keep)
    at, code, anchor = np.concatenate(times), np.concatenate(codes), np.concatenate(rank)
    order = np.lexsort((code, anchor))
    at, code, anchor = at[order], code[order], anchor[order]
    nth = np.arange(len(anchor)) - np.searchsorted(anchor, anchor)
    keep = nth < FAN
    return at[keep].astype("<i4"), code[keep].astype("<i4")


def fingerprint(payload: bytes) -> tuple[int, np.ndarray, np.ndarray]:
    level = levels(np.frombuffer(payload, np.uint8))
    return len(level), *pairs(*peaks(level))


def _media(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    raws = [x.encode() for x in texts_of(batch)]
    yield rows_out(
        MEDIA_FIELDS, doc_id=batch.column("doc_id"), n_bytes=list(map(len, raws)), media=[to_wav(padded(x)) for x in raws]
    )


def to_media(docs: DataFrame) -> DataFrame:
    """Each text's WAV file: doc_id, n_bytes, media."""
    return arrow_map(docs.select(F.col("doc_id").cast("long"), "text"), _media, MEDIA_DDL)


def _read(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    got: dict[str, list] = {f.name: [] for f in READ_FIELDS if f.name not in ("doc_id", "n_bytes", "media")}
    known: dict[bytes, tuple] = {}
    for media in batch.column("media").to_pylist():
        if media not in known:
            payload = from_wav(media)
            n, at, codes = fingerprint(payload)
            shown = hashlib.sha256(at.tobytes() + codes.tobytes()).hexdigest()[:32]
            sums = hashlib.sha256(payload).hexdigest(), hashlib.sha256(media).hexdigest()
            known[media] = (len(payload), sums[0], zlib.crc32(payload[-16:]), len(media), sums[1], f"{n}:{len(at)}:{shown}", n, at, codes)
        for name, value in zip(got, known[media], strict=True):
            got[name].append(value)
    yield rows_out(READ_FIELDS, doc_id=batch.column("doc_id"), n_bytes=batch.column("n_bytes"), media=batch.column("media"), **got)


def media_features(media: DataFrame) -> DataFrame:
    """Files of a ``media`` column read back: sizes and digests of payload and file, the fingerprint as time-coded arrays
    (``times`` ascending, ``codes`` beside them) and in short as ``feature``, and the file itself."""
    return arrow_map(media.select("doc_id", "n_bytes", "media"), _read, READ_DDL, column="media")


def op1_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files are written as a table first; what is returned comes from the bytes read from there."""
    return media_features(stored(to_media(documents(spark, sf_dir)), "media"))
