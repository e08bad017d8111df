import hashlib
import random
from collections import Counter

import numpy as np
import pytest

from spark_nlops.llm import suffix_dedup as S


def slow(texts, length=200):
    seen = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        gone = bytearray(len(t))
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        kept = bytes(b for b, g in zip(t, gone) if not g)
        runs = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        out.append((len(t), sum(gone), runs, hashlib.sha256(kept).hexdigest()))
    return out


def made_up(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randrange(1, 8)))
    text = lambda n: " ".join(word() for _ in range(n))
    shared = [text(n) for n in (30, 55, 120, 400)]
    texts = ["", "short", text(300), "a" * 700, "ab" * 400, "a" * 199, "xyz" * 67]
    for _ in range(60):
        parts = [text(rng.randrange(60))]
        for _ in range(rng.randrange(4)):
            s = rng.choice(shared)
            a = rng.randrange(len(s) // 2)
            parts += [s[a : a + rng.randrange(150, 900)], text(rng.randrange(40))]
        texts.append(" ".join(parts))
    texts += [texts[10], texts[11] + "!", texts[12][5:]]
    return texts


@pytest.mark.parametrize("hot", [S.CROWD, 2])
@pytest.mark.parametrize("scan", [1 << 18, 1000])
def test_made_up_texts(spark, monkeypatch, hot, scan):
    monkeypatch.setattr(S, "CROWD", hot)
    monkeypatch.setattr(S, "SCAN_BYTES", scan)
    texts = made_up(hot + scan)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in S.remove_repeats(df, digest_only=True).collect()}
    want = slow([t.encode() for t in texts])
    assert sum(w[1] for w in want) > 5000
    for i, w in enumerate(want):
        assert got[i] == w, (i, texts[i][:50])


def test_whole_table(spark, sf001):
    rows = spark.read.parquet(f"{sf001}/documents.parquet").collect()
    want = slow([r.text.encode() for r in rows])
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in S.op5_suffix_dedup(spark, sf001).collect()}
    assert got == {r.doc_id: w for r, w in zip(rows, want)}


def removed(spark, texts, **more):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [(r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sorted(S.remove_repeats(df, digest_only=True, **more).collect())]


def test_shared_passages_below_the_length(spark):
    rng = random.Random(9)
    line = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    shared = line(150)
    texts = [line(300) + shared + line(300) for _ in range(4)]
    want = slow([t.encode() for t in texts])
    assert removed(spark, texts) == want and not any(w[1] for w in want)
    part = S._runs_frame(S.pd.DataFrame({"group": [1, 1], "digest": [2, 3], "copies": [1, 1], "piece": [t[:250].encode() for t in texts[:2]]}), 200)
    assert not len(part) and part["low"].dtype == object  # lists, even where there are none


def test_crowds_of_one_anchor(spark, monkeypatch):
    """A passage in very many surroundings: cut to blocks, then to narrower ones, then to single windows."""
    monkeypatch.setattr(S, "CROWD", 3)
    rng = random.Random(12)
    line = lambda n: "".join(rng.choice("abcd") for _ in range(n))
    for length, size in ((200, 190), (200, 197), (200, 199), (200, 230), (131, 128)):
        shared = line(size)
        tails = [line(5) for _ in range(4)]
        texts = [line(rng.randrange(60, 300)) + shared + rng.choice(tails) + line(rng.randrange(60, 300)) for _ in range(40)]
        assert removed(spark, texts, length=length) == slow([t.encode() for t in texts], length)


def test_edges(spark):
    long = "".join(chr(97 + i * i % 23) for i in range(5000))
    rows = [(1, None, 0), (2, "", 0), (None, long, 0), (None, "é" * 99 + "x", 1), (7, "tiny", 1), (7, "tiny", 1), (8, long[:1000], 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, mark int")
    got = S.remove_repeats(df).collect()
    assert len(got) == len(rows)
    want = sorted(slow([(t or "").encode() for _, t, _ in rows]))
    assert sorted((r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == want
    assert S.remove_repeats(df.limit(0)).count() == 0


def test_kept_text_has_whole_characters():
    data = "aé漢b".encode()
    assert S.whole_characters(data, [(2, 4)]) == [] and S.whole_characters(data, [(1, 5)]) == [(1, 3)]
    assert S.merged([5, 0, 20, 1], [9, 5, 21, 2]) == [(0, 9), (20, 21)] and S.merged(None, None) == []


@pytest.mark.parametrize("seed", range(6))
def test_interval_expansion_against_counting(seed):
    rng = random.Random(seed)
    pieces = ["".join(rng.choice("ab") for _ in range(rng.randrange(1, 60))) for _ in range(30)]
    text = np.array([0] + [c for p in pieces for c in [*(ord(x) for x in p), 0]])
    for length in (1, 3, 6, 9):
        found = S.repeated_positions(text, length)
        grams = Counter(tuple(text[i : i + length]) for i in range(len(text) - length + 1))
        for i in range(len(text) - length + 1):
            g = tuple(text[i : i + length])
            if 0 not in g:
                assert found[i] == (grams[g] > 1), (length, i)
