import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from spark_nlops.llm import tiling as T


def slow_cover(doc, item, least):
    """Greedy tiling by plain search."""
    mark_d, mark_i = [False] * len(doc), [False] * len(item)
    total = 0
    while True:
        best = (least - 1, 0, 0)
        for a in range(len(doc)):
            for b in range(len(item)):
                n = 0
                while a + n < len(doc) and b + n < len(item) and doc[a + n] == item[b + n] and not mark_d[a + n] and not mark_i[b + n]:
                    n += 1
                if n > best[0]:
                    best = (n, a, b)
        n, a, b = best
        if n < least:
            return total
        mark_d[a : a + n] = [True] * n
        mark_i[b : b + n] = [True] * n
        total += n


def test_tiles_against_plain_search():
    rng = random.Random(2)
    for _ in range(60):
        item = [rng.randrange(1, 30) for _ in range(rng.randrange(3, 40))]
        doc = [rng.randrange(1, 30) for _ in range(20)]
        for _ in range(3):
            a = rng.randrange(len(item))
            doc += item[a : a + rng.randrange(1, 15)] + [0] * rng.randrange(2)
        tiles = T.tile(np.array(doc), np.array(item), 3)
        for a, b, n in tiles:
            assert doc[a : a + n] == item[b : b + n] and n >= 3
        got = sum(t[2] for t in tiles)
        # equally long matches may be marked in another order, which moves the total a little
        assert abs(got - slow_cover(doc, item, 3)) <= 3


def test_repetitive_texts_take_little_memory():
    item = " ".join(["ha"] * 2000)
    known = T.Benchmark([(1, item), (2, "ha " * 7 + "ho")], 5)
    assert known.compare("ha " * 100_000, 0.6) == [(1, 1.0), (2, 7 / 8)]
    tiles = T.tile(np.array([1, 1, 1, 1, 1, 2, 1, 1, 1]), np.array([1, 1, 1, 1]), 3)
    assert tiles == [(0, 0, 4)]


def test_rolling_hashes_are_free_of_place():
    rng = np.random.default_rng(4)
    x = rng.integers(0, 5, 400)
    for size in (1, 2, 7):
        h = T.run_hashes(x, size)
        windows = [tuple(x[i : i + size]) for i in range(len(x) - size + 1)]
        assert len(h) == len(windows) and len(set(h.tolist())) == len(set(windows)) == len(set(zip(h.tolist(), windows)))
        assert (T.run_hashes(np.concatenate(([9, 8, 7], x)), size)[3:] == h).all()


def test_reordered_passage_is_found():
    words = [f"w{i}" for i in range(40)]
    item = " ".join(words)
    known = T.Benchmark([(5, item), (6, "other words that nobody uses at all here")], 5)
    assert known.compare(" ".join(["x"] * 9 + words[20:] + ["y"] * 3 + words[:20]), 0.6) == [(5, 1.0)]
    assert known.compare("Lead in. " + item.upper() + "!", 0.6) == [(5, 1.0)]
    assert known.compare(" ".join(words[:20]), 0.6) == []
    assert known.compare(" ".join(w for i in range(0, 40, 4) for w in (*words[i : i + 4], "z")), 0.6) == []


def test_whole_table(spark, sf01):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf01}/documents.parquet").collect()}
    items = {r.item_id: r.text for r in spark.read.parquet(f"{sf01}/benchmark.parquet").collect()}
    got = {r.doc_id: r for r in T.op10_benchmark_tiling(spark, sf01).collect()}
    assert len(got) == len(docs)
    verbatim = {d for d, t in docs.items() if any(x in t for x in items.values())}
    assert verbatim and all(got[d].contaminated and got[d].coverage > 0.95 for d in verbatim)
    norm = lambda t: T.words_of(t.lower())
    numbers: dict = {}
    encode = lambda t: [numbers.setdefault(w, len(numbers) + 1) for w in norm(t)]
    rng = random.Random(1)
    for d in rng.sample(sorted(docs), 25) + sorted(verbatim)[:5]:
        doc = encode(docs[d])[:150]
        want = any(slow_cover(doc, encode(x), 5) >= 0.6 * len(norm(x)) for x in rng.sample(sorted(items.values()), 4))
        assert not want or got[d].contaminated


def test_edges(spark):
    docs = spark.createDataFrame([(1, None, 0), (2, "", 0), (None, "a b c d e f", 0), (3, "tiny item", 1), (3, "tiny item", 1), (4, "a b " * 40_000, 1)], "doc_id long, text string, item_id int")
    items = spark.createDataFrame([(9, "a b c d e f"), (8, "tiny item"), (7, None), (6, ""), (None, "a b"), (9, "a b c d e f")], "item_id long, text string")
    got = T.contamination(docs, items).collect()
    assert len(got) == 6
    by = {r.doc_id: [h.item for h in r.nlops_leak] for r in got}
    assert by == {1: [], 2: [], None: [9], 3: [8], 4: []}
    assert T.contamination(docs, items.limit(0)).filter("size(nlops_leak) > 0").count() == 0
    assert T.contamination(docs.limit(0), items).count() == 0
    clash = docs.withColumnsRenamed({"item_id": "row"}).withColumn("leak", F.lit("x"))
    assert T.contamination(clash, items).columns == ["doc_id", "text", "row", "leak", "nlops_leak"]
    with pytest.raises(ValueError):
        T.contamination(docs.withColumn("NLOPS_LEAK", F.lit(1)), items)


def test_benchmark_blocks(spark, monkeypatch):
    monkeypatch.setattr(T, "BLOCK_BYTES", 40)
    docs = spark.createDataFrame([(1, "one two three four five six"), (2, "red green blue pink grey")], "doc_id long, text string")
    items = spark.createDataFrame([(i, t) for i, t in enumerate(["one two three four five", "red green blue pink grey", "one two three four five six"])], "item_id long, text string")
    got = {r.doc_id: sorted(h.item for h in r.nlops_leak) for r in T.contamination(docs, items).collect()}
    assert got == {1: [0, 2], 2: [1]}


def test_items_without_an_id(spark, tmp_path):
    """The query reports what documents hold of them, with a null item_id."""
    spark.createDataFrame([(1, "x one two three four five y"), (2, "red green blue pink grey"), (3, "none of it")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(None, "one two three four five"), (None, "red green blue pink grey"), (4, "red green blue pink grey")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r.doc_id: (r.contaminated, r.item_id, r.n_items) for r in T.op10_benchmark_tiling(spark, str(tmp_path)).collect()}
    assert got == {1: (True, None, 1), 2: (True, None, 2), 3: (False, None, 0)}
