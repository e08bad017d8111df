import hashlib
import zlib

import numpy as np

from spark_nlops.llm import wav_media as W


def slow_pairs(samples):
    x = np.frombuffer(samples, np.uint8).astype(float)
    frames, start = [], 0
    while True:
        f = x[start : start + W.FRAME]
        frames.append(np.concatenate((f, np.full(W.FRAME - len(f), 128.0))))
        start += W.HOP
        if start + W.FRAME - W.HOP >= len(x):
            break
    tops = []
    for f in frames:
        p = np.abs(np.fft.rfft((f - f.mean()) * np.hanning(W.FRAME)))
        tops.append([a + int(p[a:b].argmax()) if p[a:b].max() > max(p.mean(), 1e-3) else 0 for a, b in zip(W.BANDS[:-1], W.BANDS[1:])])
    return sorted((t, (f << 12) | (g << 4) | d) for t, row in enumerate(tops) for d in range(1, W.REACH + 1) if t + d < len(tops) for f in row if f for g in tops[t + d] if g)


def test_pairs_against_loops():
    rng = np.random.default_rng(1)
    t = np.arange(5000)
    tone = (128 + 60 * np.sin(t * 0.3) + 40 * np.sin(t * 1.1) + rng.normal(0, 3, 5000)).astype(np.uint8).tobytes()
    for samples in (tone, bytes(64), tone[:256], tone[:257], tone[:448]):
        times, codes = W.pair_codes(W.spectral_peaks(samples)[0])
        assert list(zip(times.tolist(), codes.tolist())) == slow_pairs(samples)
    assert len(slow_pairs(tone)) > 50


def test_round_trip_of_whole_table(spark, sf001):
    rows = {r.doc_id: r.text for r in spark.read.parquet(f"{sf001}/documents.parquet").collect()}
    got = W.op7_wav_fingerprints(spark, sf001).collect()
    assert len(got) == len(rows)
    for r in got:
        data = rows[r.doc_id].encode()
        padded = data.ljust(max(64, -(-len(data) // 64) * 64), b"\0")
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(data), len(padded), hashlib.sha256(padded).hexdigest())
        assert r.tail_crc32 == zlib.crc32(padded[-64:])
        assert W.read_wav(bytes(r.media)) == padded and r.media_bytes == len(r.media)
        times, codes = W.pair_codes(W.spectral_peaks(padded)[0])
        assert r.pair_times == times.tolist() and r.pair_codes == codes.tolist()


def test_edges(spark):
    rows = [(1, None), (2, ""), (None, "x"), (3, "long " * 100_000), (4, "long " * 100_000)]
    df = spark.createDataFrame([(*r, b"m") for r in rows], "doc_id long, text string, media binary")
    got = {r.doc_id: r for r in W.fingerprint_documents(df).collect()}
    assert got[1].payload_bytes == got[2].payload_bytes == got[None].payload_bytes == 64 and got[1].media == got[2].media
    assert W.read_wav(bytes(got[3].media))[: len("long " * 100_000)] == b"long " * 100_000
    assert got[3].feature == got[4].feature and list(got[1].pair_codes) == []
    assert W.fingerprint_documents(df.limit(0)).count() == 0
