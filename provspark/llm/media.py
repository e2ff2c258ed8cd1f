"""Operator 10, media columns: texts as WAV samples, STFT and spectral-peak pair fingerprints.

A document's bytes become the samples of an 8-bit mono WAV held in a binary column.  The
column is written, read back with the ``wave`` module and described by the pairs of spectral
peaks of its short-time Fourier transform, kept as time-coded arrays.

Defined cases: a null text is the empty text; the payload of an empty text is 64 zero bytes;
a null id stays null; repeated rows give repeated results; only the id and text columns are
read, so other columns of any name do no harm; an empty table gives an empty result; of equally loud frames all are peaks,
and of equally strong bins the lowest is the frame's.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provspark.llm.common import map_arrow, read_table, text_bytes, write_read

BLOCK = 64  # payloads are padded to a positive multiple of this
RATE = 8000
FRAME, HOP = 64, 32
SPREAD = 2  # a peak is the loudest frame among so many on either side
FAN = 3  # a peak is paired with so many following ones
FRAMES_AT_ONCE = 1 << 15
WINDOW = np.hanning(FRAME).astype(np.float32)


def payload_of(raw: bytes) -> bytes:
    return raw + b"\0" * ((-len(raw)) % BLOCK if raw else BLOCK)


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


def spectral_peaks(samples: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Loudest bin and its size for each frame, in blocks of frames: (bin, size, is_peak)."""
    x = np.frombuffer(samples, np.uint8)
    n = max(1, (len(x) - FRAME) // HOP + 1)
    bins, size = np.empty(n, np.int32), np.empty(n, np.float32)
    for a in range(0, n, FRAMES_AT_ONCE):
        b = min(n, a + FRAMES_AT_ONCE)
        part = x[a * HOP : (b - 1) * HOP + FRAME].astype(np.float32) - 128
        frames = np.lib.stride_tricks.sliding_window_view(part, FRAME)[::HOP] * WINDOW
        power = np.abs(np.fft.rfft(frames, axis=1)[:, 1:])
        top = power.argmax(axis=1)
        bins[a:b] = top + 1
        size[a:b] = power[np.arange(b - a), top]
    around = np.pad(size, SPREAD, constant_values=-1)
    loudest = np.lib.stride_tricks.sliding_window_view(around, 2 * SPREAD + 1).max(axis=1)
    return bins, size, (size >= loudest) & (size > 0)


def peak_pairs(samples: bytes) -> tuple[np.ndarray, np.ndarray, int]:
    """Time codes and codes (first bin, second bin, distance) of peak pairs; number of frames."""
    bins, _, peak = spectral_peaks(samples)
    at = np.flatnonzero(peak)
    times, codes = [], []
    for k in range(1, FAN + 1):
        a, b = at[:-k], at[k:]
        times.append(a)
        codes.append(bins[a] << 22 | bins[b] << 16 | np.minimum(b - a, 0xFFFF))
    t, c = np.concatenate(times).astype(np.int32), np.concatenate(codes).astype(np.int32)
    order = np.lexsort((c, t))
    return t[order], c[order], len(bins)


def media_column(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, n_bytes, media): the text's padded bytes as a WAV in a binary column."""
    kind = df.schema[id_col].dataType.simpleString()

    def per_slice(batch):
        raw = text_bytes(batch.column("text")).to_pylist()
        return pa.RecordBatch.from_arrays(
            [batch.column("id"), pa.array([len(x) for x in raw], pa.int64()), pa.array([to_wav(payload_of(x)) for x in raw], pa.binary())],
            names=["id", "n_bytes", "media"],
        )

    return map_arrow(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), f"id {kind}, n_bytes long, media binary", "text", per_slice)


FINGERPRINT = (
    "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, "
    "n_frames long, pair_times array<int>, pair_codes array<int>"
)


def fingerprints(media: DataFrame) -> DataFrame:
    """Read each stored WAV and describe it; the peak pairs are two arrays, of time codes and of codes."""
    kind = media.schema["id"].dataType.simpleString()

    def per_slice(batch):
        cols = {x.split()[0]: [] for x in FINGERPRINT.split(", ")}
        for m in batch.column("media").to_pylist():
            payload = from_wav(m)
            t, c, frames = peak_pairs(payload)
            row = (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-BLOCK:]), len(m), hashlib.sha256(m).hexdigest(), frames, t, c)
            for k, v in zip(cols, row):
                cols[k].append(v)
        types = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32())]
        return pa.RecordBatch.from_arrays(
            [batch.column("id"), batch.column("n_bytes"), *(pa.array(v, t) for v, t in zip(cols.values(), types))],
            names=["id", "n_bytes", *cols],
        )

    return map_arrow(media, f"id {kind}, n_bytes long, {FINGERPRINT}", "media", per_slice)


def feature_of() -> F.Column:
    """"frames:pairs:digest" of a row of fingerprints, the digest being that of its two arrays."""
    digest = F.concat(*[F.lower(F.lpad(F.hex(F.xxhash64(F.lit(seed), "pair_times", "pair_codes")), 16, "0")) for seed in (1, 2)])
    return F.concat_ws(":", "n_frames", F.size("pair_times"), digest)


def op10_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    stored = write_read(media_column(read_table(spark, sf_dir, "documents")), "media", compression="zstd")
    prints = write_read(fingerprints(stored), "fingerprints", compression="zstd")
    return prints.select(F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", feature_of().alias("feature"))
