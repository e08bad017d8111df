"""Media columns: lossless WAV storage and spectral-peak pair fingerprints.

A payload is stored as 8-bit mono samples with the ``wave`` module and read back
with it.  The samples' short-time Fourier transform is cut into frequency bands;
each band's strongest bin of a frame is a peak if it stands out from the frame.
A peak is paired with the peaks of the next frames; a pair's code holds both
frequencies and their distance, and codes are kept with their frame numbers, in
order of time.

Defined results: null and empty texts have a payload of 64 zero bytes; silence
has no peaks, so empty code arrays; the lower bin wins ties; equal payloads give
equal files and fingerprints; null keys are carried along; an empty table gives
an empty table; other columns are not read.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table, slices, text_or_empty

RATE, FRAME, HOP = 8000, 256, 128
#: Borders of the frequency bands (bins of the transform) and the frames a peak is paired with.
BANDS, REACH = (2, 12, 32, 64, 129), 3
#: Frames transformed together.
FRAMES = 4096
_WINDOW = np.hanning(FRAME).astype(np.float32)


def payload_of(text: str, block: int = 64) -> tuple[int, bytes]:
    data = text.encode()
    return len(data), data + bytes(-len(data) % block if data else block)


def write_wav(payload: bytes, rate: int = RATE) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(rate)
        w.writeframes(payload)
    return out.getvalue()


def read_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as r:
        if r.getsampwidth() != 1 or r.getnchannels() != 1:
            raise ValueError("8-bit mono samples are expected")
        return r.readframes(r.getnframes())


def spectral_peaks(samples: bytes) -> tuple[np.ndarray, int]:
    """For each frame the peak bin of each band (0: none), and the number of frames."""
    x = np.frombuffer(samples, dtype=np.uint8)
    frames = max(1, -(-(len(x) - FRAME) // HOP) + 1)
    x = np.concatenate((x, np.full((frames - 1) * HOP + FRAME - len(x), 128, dtype=np.uint8))) if (frames - 1) * HOP + FRAME > len(x) else x
    view = np.lib.stride_tricks.sliding_window_view(x, FRAME)[::HOP]
    peaks = np.zeros((frames, len(BANDS) - 1), dtype=np.int64)
    for a in range(0, frames, FRAMES):
        part = view[a : min(a + FRAMES, frames)].astype(np.float32)
        part -= part.mean(axis=1, keepdims=True)
        power = np.abs(np.fft.rfft(part * _WINDOW, axis=1))
        floor = np.maximum(power.mean(axis=1), 1e-3)
        for b, (low, high) in enumerate(zip(BANDS[:-1], BANDS[1:])):
            band = power[:, low:high]
            top = band.argmax(axis=1)
            strong = band[np.arange(len(band)), top] > floor
            peaks[a : a + len(band), b] = np.where(strong, top + low, 0)
    return peaks, frames


def pair_codes(peaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frame numbers and codes of the peak pairs, by time, then code."""
    times, codes = [], []
    for gap in range(1, REACH + 1):
        if len(peaks) <= gap:
            break
        early, late = peaks[:-gap, :, None], peaks[gap:, None, :]
        at, b1, b2 = np.nonzero((early > 0) & (late > 0))
        times.append(at)
        codes.append((peaks[at, b1] << 12) | (peaks[at + gap, b2] << 4) | gap)
    if not times:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    times, codes = np.concatenate(times), np.concatenate(codes)
    order = np.lexsort((codes, times))
    return times[order], codes[order]


def fingerprint_documents(docs: DataFrame, *, key: str = "doc_id", text: str = "text", digest_only: bool = False) -> DataFrame:
    """key, sizes and digests of payload and file and, unless digest_only, the file and its time-coded pairs."""
    extra = "" if digest_only else ", media binary, pair_times array<int>, pair_codes array<int>"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for a, b in slices(batch["text"].map(len).tolist(), 4_000_000):
                rows = []
                for t in batch["text"].iloc[a:b]:
                    n, payload = payload_of(t)
                    media = write_wav(payload)
                    stored = read_wav(media)
                    peaks, frames = spectral_peaks(stored)
                    times, codes = pair_codes(peaks)
                    digest = hashlib.md5(times.astype("<i4").tobytes() + codes.astype("<i4").tobytes()).hexdigest()
                    feature = f"frames={frames};peaks={int((peaks > 0).sum())};pairs={len(codes)};codes={digest}"
                    row = (n, len(stored), hashlib.sha256(stored).hexdigest(), zlib.crc32(stored[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature)
                    rows.append(row if digest_only else (*row, media, times.astype(np.int32), codes.astype(np.int32)))
                names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
                names += [] if digest_only else ["media", "pair_times", "pair_codes"]
                yield pd.DataFrame({"key": batch["key"].array[a:b]} | {c: [r[i] for r in rows] for i, c in enumerate(names)})

    kind = docs.schema[key].dataType.simpleString()
    schema = f"key {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string{extra}"
    return docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInPandas(run, schema).withColumnRenamed("key", key)


def op7_wav_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_documents(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
