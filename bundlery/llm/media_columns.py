"""Audio media columns: lossless WAV storage and spectral-peak fingerprints.

Each payload is stored as 8-bit mono PCM by the ``wave`` module and read back
through it.  A short-time Fourier transform of the samples read gives a
spectrogram; the strongest bin of a band is a peak where it is no weaker than
that of the frames beside it, and each peak is paired with the next few peaks.
A pair is one integer that leads with the time of its first peak, so the array
of a medium is ordered and coded by time.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textbits import slices

RATE, FRAME, HOP = 8000, 256, 128
#: Peaks that one peak is paired with, and the furthest of them in frames.
FAN, REACH = 2, 63
#: Bands of frequency bins; each may hold a peak in every frame.
BANDS = ((2, 16), (16, 40), (40, 80), (80, 129))
_HANN = np.hanning(FRAME).astype(np.float32)


def to_wav(samples: bytes) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(samples)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as r:
        return r.readframes(r.getnframes())


def peak_pairs(samples: bytes) -> np.ndarray:
    """Pairs of spectral peaks: ``time << 24 | bin << 16 | bin << 8 | distance``."""
    x = np.frombuffer(samples, np.uint8).astype(np.float32) - 128
    # silence up to a whole number of hops, so that every sample is in a frame
    x = np.pad(x, (0, max(FRAME - len(x), (FRAME - len(x)) % HOP)))
    frames = np.lib.stride_tricks.sliding_window_view(x, FRAME)[::HOP]
    best, level = np.empty((len(frames), len(BANDS)), np.int64), np.empty((len(frames), len(BANDS)), np.float32)
    for at in range(0, len(frames), 4096):
        s = np.fft.rfft(frames[at : at + 4096] * _HANN, axis=1)
        power = s.real**2 + s.imag**2
        for k, (lo, hi) in enumerate(BANDS):
            best[at : at + 4096, k] = power[:, lo:hi].argmax(axis=1) + lo
            level[at : at + 4096, k] = power[:, lo:hi].max(axis=1)
    around = np.pad(level, ((1, 1), (0, 0)), constant_values=-1.0)
    # by time, then by band
    time, band = np.nonzero((level >= around[:-2]) & (level > around[2:]) & (level > 0))
    pitch, out = best[time, band], []
    for step in range(1, FAN + 1):
        near = time[step:] - time[: max(0, len(time) - step)] <= REACH
        a, b = np.flatnonzero(near), np.flatnonzero(near) + step
        out.append((time[a] << 24) | (pitch[a] << 16) | (pitch[b] << 8) | (time[b] - time[a]))
    return np.sort(np.concatenate(out))


def media_columns(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media, fingerprint``.

    The payload is the text's UTF-8 with bytes 0 up to a positive multiple of
    64; null and empty texts are 64 zero bytes.  Digests and fingerprints are of
    what is read back from ``media``.  Equal texts give equal values.
    """
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("text"))

    def run(batches):
        for part in slices(batches):
            rows = []
            for raw in part.column(1).to_pylist():
                raw = raw or b""
                media = to_wav(raw + bytes(max(64, -len(raw) % 64 + len(raw)) - len(raw)))
                back = from_wav(media)
                rows.append((len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), media, peak_pairs(back)))
            n, m, sha, crc, media, pairs = zip(*rows)
            ends = np.cumsum([0, *map(len, pairs)]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(n, pa.int64()), pa.array(m, pa.int64()), pa.array(sha), pa.array(crc, pa.int64()), pa.array(media, pa.binary()), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(pairs).astype(np.int64)))],
                ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media", "fingerprint"],
            )

    return source.mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media binary, fingerprint array<long>")
