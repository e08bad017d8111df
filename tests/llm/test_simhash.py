import random
import re

import numpy as np
import xxhash

from spark_nlops.llm import simhash
from spark_nlops.llm.common import Stage
from spark_nlops.llm.graph import connected_components


def slow_fingerprint(text):
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)
    words = re.findall(r"[^\x20\x09-\x0D]+", lowered)
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)] if words else []
    hashes = [xxhash.xxh64(g.encode(), seed=42).intdigest() for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def slow_components(prints):
    ids = list(prints)
    part = {i: i for i in ids}

    def find(x):
        while part[x] != x:
            x = part[x]
        return x

    for n, a in enumerate(ids):
        for b in ids[:n]:
            if (prints[a] ^ prints[b]).bit_count() <= 2:
                x, y = find(a), find(b)
                part[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_whole_table_against_brute_force(spark, sf001):
    rows = spark.read.parquet(f"{sf001}/documents.parquet").collect()
    prints = {r.doc_id: slow_fingerprint(r.text) for r in rows}
    parts = slow_components(prints)
    got = {r.doc_id: r for r in simhash.op3_simhash_near_dedup(spark, sf001).collect()}
    assert {i: r.fingerprint for i, r in got.items()} == {i: f"{v:016x}" for i, v in prints.items()}
    assert {i: r.component_id for i, r in got.items()} == parts


def test_edges(spark):
    texts = [(9, None), (4, ""), (7, " \t\n"), (1, "One"), (2, "one"), (3, "a b"), (None, "a b"), (5, "word " * 50_000), (6, "word " * 50_000)]
    df = spark.createDataFrame([(i, t, 0, "x") for i, t in texts], "doc_id long, text string, fp int, rep string")
    got = {r.doc_id: r for r in simhash.near_duplicates(df).collect()}
    assert len(got) == len(texts)
    assert [got[i].fp for i in (9, 4, 7)] == [0, 0, 0] and [got[i].component for i in (9, 4, 7)] == [4, 4, 4]
    assert got[1].component == got[2].component == 1 and got[6].component == 5
    assert got[None].component is None
    assert simhash.near_duplicates(df.limit(0)).count() == 0


def test_forest_links_what_is_near():
    rng = random.Random(5)
    base = [rng.getrandbits(64) for _ in range(6)]
    values = []
    for b in base:
        for _ in range(60):
            x = b
            for _ in range(rng.randrange(4)):
                x ^= 1 << rng.randrange(16)
            values.append(x)
    values = list(dict.fromkeys(values))
    root = simhash.linked_forest(np.zeros(len(values), int), np.array(values, dtype=np.uint64))
    parts = slow_components(dict(enumerate(values)))
    groups = lambda m: {frozenset(i for i in m if m[i] == r) for r in m.values()}
    assert groups(dict(enumerate(root.tolist()))) == groups(parts)


def test_components_of_chains_and_hubs(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 180)] + [(5, 5), (300, 299), (299, 300)]
    df = spark.createDataFrame(edges, "a long, b long")
    got = {r.node: r.component for r in connected_components(df, Stage(spark, "test")).collect()}
    assert got == {i: 0 for i in range(41)} | {i: 100 for i in range(100, 180)} | {299: 299, 300: 299}
    assert connected_components(df.limit(0), Stage(spark, "test")).count() == 0


def slow_similar(texts, similarity=0.8):
    sets = {}
    for i, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[i] = {b" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    ids = sorted(sets)
    part = {i: i for i in ids}

    def find(x):
        while part[x] != x:
            x = part[x]
        return x

    for n, a in enumerate(ids):
        for b in ids[:n]:
            x, y = sets[a], sets[b]
            if min(len(x), len(y)) >= similarity * max(len(x), len(y)) and len(x & y) >= similarity * len(x | y):
                p, q = find(a), find(b)
                part[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}


def test_similar_documents_against_all_pairs(spark, sf01):
    rows = {r.doc_id: r.text for r in spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text").collect()}
    want = slow_similar(rows)
    got = {r.doc_id: r.component for r in simhash.similar_documents(spark.read.parquet(f"{sf01}/documents.parquet")).collect()}
    assert len(set(want.values())) < len(want) - 50
    assert got == want


def test_similar_documents_in_large_groups(spark, monkeypatch):
    """More near copies of one text than a bucket compares in pairs."""
    monkeypatch.setattr(simhash, "ALL_PAIRS", 8)
    rng = random.Random(3)
    base = [f"w{rng.randrange(5000)}" for _ in range(300)]
    texts = {7: " ".join(base)}
    for i in range(100, 180):
        words = list(base)
        for _ in range(5):
            words[rng.randrange(300)] = f"x{rng.randrange(10**6)}"
        texts[i] = " ".join(words)
    texts |= {1: " ".join(f"v{rng.randrange(5000)}" for _ in range(300)), 2: "", 3: "", 4: "a b", 5: "A  b", 6: "b a"}
    df = spark.createDataFrame([*texts.items(), (None, "a b")], "doc_id long, text string")
    got = {r.doc_id: r.component for r in simhash.similar_documents(df).collect()}
    assert {i: c for i, c in got.items() if i is not None} == slow_similar(texts) and got[None] is None
    assert simhash.similar_documents(df.limit(0)).count() == 0


def shared_passage(n):
    """Pairs of near copies in texts of which 79 % is one passage; texts of different pairs are less similar than 0.8."""
    rng = random.Random(1)
    words = lambda n, p: [f"{p}{rng.randrange(10**7)}" for _ in range(n)]
    passage, texts = words(237, "s"), {}
    for k in range(n):
        own = words(63, "o")
        texts[2 * k] = " ".join(passage + own)
        own[rng.randrange(63)] = f"z{k}"
        texts[2 * k + 1] = " ".join(passage + own)
    return texts


def test_similar_documents_that_meet_in_large_buckets_only(spark, monkeypatch):
    texts = shared_passage(100)
    want = slow_similar(texts)
    assert len(set(want.values())) == 100
    df = spark.createDataFrame([*texts.items()], "doc_id long, text string")
    monkeypatch.setattr(simhash, "BLOCK", 16)  # more than one block
    assert {r.doc_id: r.component for r in simhash.similar_documents(df).collect()} == want


def test_prefix_pairs_that_have_to_be_drawn(spark, monkeypatch):
    """A chain of texts without a common source: many candidates, of which a random part is verified first."""
    rng = random.Random(4)
    words = [f"w{i}" for i in range(400)]
    texts = {}
    for i in range(120):
        words[(3 * i) % 400 : (3 * i) % 400 + 3] = [f"x{i}_{k}" for k in range(3)]
        texts[i] = " ".join(words)
    texts |= {1000 + i: " ".join(f"v{rng.randrange(10**6)}" for _ in range(100)) for i in range(5)}
    monkeypatch.setattr(simhash, "ALL_PAIRS", 2)
    df = spark.createDataFrame([*texts.items()], "doc_id long, text string")
    assert {r.doc_id: r.component for r in simhash.similar_documents(df).collect()} == slow_similar(texts)


def test_similar_documents_that_differ_in_repeats(spark):
    rng = random.Random(2)
    texts = {}
    for k, times in enumerate((10, 20, 40) * 3):
        words, line = ([f"{p}{rng.randrange(10**7)}" for _ in range(n)] for p, n in (("a", 200), ("l", 10)))
        texts[2 * k], texts[2 * k + 1] = " ".join(words + line), " ".join(words + line * times)
    want = slow_similar(texts)
    assert len(set(want.values())) == 9
    df = spark.createDataFrame([*texts.items()], "doc_id long, text string")
    assert {r.doc_id: r.component for r in simhash.similar_documents(df).collect()} == want


def test_parities_bound_the_difference():
    rng = np.random.default_rng(3)
    for n in (1, 40, 3000):
        x, y = (np.unique(rng.integers(0, 2**32, n, dtype=np.uint32)) for _ in range(2))
        y = np.unique(np.concatenate((x[: n // 2], y)))
        bits = np.bitwise_count((simhash.parity(x) ^ simhash.parity(y)).view(np.uint64)).sum()
        assert bits <= len(np.setxor1d(x, y))


def test_sets_of_compared_texts_only_are_written_and_pairs_in_parts(spark, monkeypatch):
    rng = random.Random(8)
    words = [f"w{rng.random()}" for _ in range(200)]
    near = [" ".join(words[:i] + ["x"] + words[i + 1 :]) for i in range(40)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(near)] + [(100 + i, f"apart {i} " + " ".join(f"{i}-{j}" for j in range(50))) for i in range(200)], "doc_id long, text string")
    grams = simhash._compared(df, "doc_id", "text", 5, spark.range(40).withColumnRenamed("id", "rep")).cache()
    assert {r.rep for r in grams.collect()} >= set(range(40)) and grams.count() < 50
    pairs = spark.createDataFrame([(a, b) for a in range(40) for b in range(a + 1, 40)], "a long, b long")
    sizes, verified = [], simhash._verified

    def counted(pairs, *more):
        sizes.append(pairs.count())
        return verified(pairs, *more)

    monkeypatch.setattr(simhash, "_verified", counted)
    stage = simhash.Stage(spark, "test")
    links = simhash._settled(pairs, pairs.limit(0), grams, 40, 0.8, stage, "links")
    assert len(sizes) > 4 and max(sizes) <= 100 and sum(sizes) < 780
    assert {(r.node, r.component) for r in simhash.connected_components(links, stage).collect()} == {(i, 0) for i in range(40)}
