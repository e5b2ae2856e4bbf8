"""Media columns: sounds as WAV bytes, their short-time spectra, and fingerprints of peak pairs.

A sound is kept in its container, a WAV image in a binary column. Features come from what the
``wave`` module reads back: a Hann-windowed short-time Fourier transform, the cells that are the
largest of their neighbourhood, and for each of them its pairs with the next peaks. A pair is a
32-bit code (two frequencies and their distance in frames) with the frame it starts at; the codes
form an array ordered by time.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import as_bytes, batch_of, let_go, small_batches, text_or_empty

RATE, WINDOW, HOP = 8000, 512, 256
#: Half the neighbourhood of a peak, in frames and bins; how many later peaks it is paired with, and how far.
NEAR_FRAMES, NEAR_BINS, FAN, REACH = 4, 8, 4, 63
HANN = (0.5 - 0.5 * np.cos(2 * np.pi * np.arange(WINDOW) / WINDOW)).astype(np.float32)
#: Frames that are transformed and searched for peaks at once, for sounds of any length.
FRAMES = 2048


def padded(data: bytes, unit: int = 64) -> bytes:
    """With zeros up to a positive multiple of ``unit``."""
    return data + b"\0" * (max(1, -(-len(data) // unit)) * unit - len(data))


def to_wav(samples: bytes) -> bytes:
    """A mono WAV image of unsigned 8-bit samples."""
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(samples)
    return out.getvalue()


def from_wav(image: bytes) -> bytes:
    with wave.open(io.BytesIO(image), "rb") as r:
        return r.readframes(r.getnframes())


def frame_count(length: int) -> int:
    """Frames of a sound of so many samples, padded with silence to a window and whole hops, so that every sample is in one."""
    return 1 + max(0, -(-(length - WINDOW) // HOP))


def spectrum(samples: bytes, first: int = 0, last: int | None = None) -> np.ndarray:
    """Magnitudes of the frames from ``first`` to before ``last``, a row for each."""
    last = frame_count(len(samples)) if last is None else last
    x = np.frombuffer(samples, np.uint8)[first * HOP : (last - 1) * HOP + WINDOW].astype(np.float32) - 128
    x = np.pad(x, (0, (last - first - 1) * HOP + WINDOW - len(x)))
    frames = np.lib.stride_tricks.sliding_window_view(x, WINDOW)[::HOP]
    return np.abs(np.fft.rfft(frames * HANN, axis=1)).astype(np.float32)


def _largest_near(a: np.ndarray, half: int, axis: int) -> np.ndarray:
    """The largest value within ``half`` of each cell along ``axis``."""
    pad = [(0, 0), (0, 0)]
    pad[axis] = (half, half)
    p, out, n = np.pad(a, pad, constant_values=-1), a, a.shape[axis]
    for k in range(2 * half + 1):
        out = np.maximum(out, p[k : k + n] if axis == 0 else p[:, k : k + n])
    return out


def peaks(samples: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Frames and bins of the cells that are largest of their neighbourhood and above the sound's mean, by time.

    FRAMES frames at a time, each time with the neighbours of the first and the last.
    """
    n, found, held = frame_count(len(samples)), [], None
    if n > FRAMES:
        total = sum(float(spectrum(samples, a, min(n, a + FRAMES)).sum(dtype=np.float64)) for a in range(0, n, FRAMES))
    else:
        held = spectrum(samples)
        total = float(held.sum(dtype=np.float64))
    mean = total / (n * (WINDOW // 2 + 1))
    for a in range(0, n, FRAMES):
        low, high = max(0, a - NEAR_FRAMES), min(n, a + FRAMES + NEAR_FRAMES)
        magnitude = held if held is not None else spectrum(samples, low, high)
        top = _largest_near(_largest_near(magnitude, NEAR_BINS, 1), NEAR_FRAMES, 0)
        t, f = np.nonzero((magnitude == top) & (magnitude > mean))
        own = (t + low >= a) & (t + low < a + FRAMES)
        found.append((t[own] + low, f[own]))
    return tuple(np.concatenate([x[i] for x in found]) for i in range(2))


def fingerprint(samples: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(frames, codes): each peak with each of its next FAN peaks within REACH frames, ordered by time."""
    t, f = peaks(samples)
    at, codes = [], []
    for k in range(1, FAN + 1):
        if len(t) > k:
            gap = t[k:] - t[:-k]
            near = gap <= REACH
            at.append(t[:-k][near])
            codes.append((f[:-k][near] << 15 | f[k:][near] << 6 | gap[near]).astype(np.int64))
    if not at:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    at, codes = np.concatenate(at), np.concatenate(codes)
    order = np.lexsort((codes, at))
    return at[order], codes[order]


def store_sounds(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id, n_bytes, media): each whole text's padded bytes as a WAV image, of any length that the format has room for.

    A null text is an empty one: 64 zeros. Repeated rows are rows of their own; columns beside the two that are read play no part, whatever their names.
    """
    small_batches(docs.sparkSession)
    schema = pa.schema([("id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary())])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        for batch in batches:
            data = as_bytes(batch.column(1))
            yield batch_of(schema, {"id": batch.column(0), "n_bytes": list(map(len, data)), "media": [to_wav(padded(x)) for x in data]})

    return docs.select(docs[id_col].cast("long").alias("id"), text_or_empty(text_col)).mapInArrow(encode, "id long, n_bytes long, media binary")


def sound_features(sounds: DataFrame) -> DataFrame:
    """(id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, frames, codes) of stored sounds.

    All but the first two come from the stored images. Silence has no peaks and gives empty arrays;
    sounds of any length are transformed in portions; repeated rows are rows of their own.
    """
    ints = pa.list_(pa.int32())
    schema = pa.schema([("id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("frames", ints), ("codes", ints)])

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: dict[str, list] = {f.name: [] for f in schema}
            for image in batch.column(2).to_pylist():
                samples = from_wav(image)
                frames, codes = fingerprint(samples)
                for k, v in (("payload_bytes", len(samples)), ("payload_sha256", hashlib.sha256(samples).hexdigest()), ("tail_crc32", zlib.crc32(samples[-64:])), ("media_bytes", len(image)), ("media_sha256", hashlib.sha256(image).hexdigest()), ("frames", frames.astype(np.int32)), ("codes", codes.astype(np.int32))):
                    rows[k].append(v)
            yield batch_of(schema, rows | {"id": batch.column(0), "n_bytes": batch.column(1)})

    return sounds.mapInArrow(decode, "id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, frames array<int>, codes array<int>")
