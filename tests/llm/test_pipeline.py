from pyspark.sql import functions as F

import corpus_pipeline as C
from spark_nlops.llm import bpe, langid, tiling

from .test_simhash import slow_components, slow_fingerprint, slow_similar
from .test_suffix_dedup import slow as slow_repeats


def test_stages_against_brute_force(spark, sf001, tmp_path):
    docs = spark.read.parquet(f"{sf001}/documents.parquet")
    columns = docs.columns
    kept = []
    for name, function in C.STAGES:
        function(spark, docs, sf001).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        kept.append({r.doc_id: r for r in docs.collect()})
        if name != C.STAGES[-1][0]:
            assert docs.columns == columns
    source = {r.doc_id: r for r in spark.read.parquet(f"{sf001}/documents.parquet").collect()}
    told, single, cut, clean, encoded = kept
    assert all(langid.has_letter(r.text) for r in told.values()) and len(told) > 0.95 * len(source)
    parts = slow_components({i: slow_fingerprint(r.text) for i, r in told.items()})
    alike = slow_similar({i: r.text for i, r in told.items()})
    merged = dict(parts)
    for _ in range(10):  # least id over both kinds of groups, until nothing moves
        for groups in (parts, alike):
            least = {}
            for i, g in groups.items():
                least[g] = min(least.get(g, i), merged[i])
            merged = {i: min(merged[i], least[groups[i]]) for i in merged}
    assert set(single) == {i for i in told if merged[i] == i}
    wanted = slow_repeats([single[i].text.encode() for i in sorted(single)])
    for i, (size, gone, _, _) in zip(sorted(single), wanted):
        left = len(cut[i].text.encode())
        assert size - gone <= left <= size - gone + 6 * 20 and cut[i].n_chars == len(cut[i].text)
        assert gone or cut[i].text == single[i].text
    items = [r.text for r in spark.read.parquet(f"{sf001}/benchmark.parquet").collect()]
    known = tiling.Benchmark(list(enumerate(items)), tiling.SEED)
    assert set(clean) == {i for i, r in cut.items() if not known.compare(r.text, tiling.THRESHOLD)}
    path, pattern = bpe.default_vocabulary()
    codec = bpe.Codec(bpe.vocabulary_bytes(path), pattern)
    assert set(encoded) == set(clean)
    assert all(codec.decode(r.ids).decode() == clean[i].text for i, r in encoded.items())


def test_run_gives_the_last_stage(spark, sf001):
    out = C.run(spark, sf001)
    assert out.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "ids"] and out.count() > 100


def test_stages_on_edges(spark, sf001):
    rows = [(1, None, "en", "s", None), (None, "The cat sat on the mat and the dog ran", "en", "s", 5), (2, "", "en", "s", 0), (2, "", "en", "s", 0), (3, "the and " * 60_000, None, None, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for _, function in C.STAGES:
        function(spark, docs, sf001).collect()
        assert function(spark, docs.limit(0), sf001).count() == 0


def test_stages_keep_columns_of_their_own_names(spark, sf001):
    """Extra columns with the names that the stages use within."""
    names = ["nlops_language", "nlops_row", "nlops_own", "nlops_lows", "nlops_leak", "row", "leak", "key", "doc", "mark", "component", "rep"]
    docs = spark.read.parquet(f"{sf001}/documents.parquet").limit(60).withColumns({c: F.lit(c) for c in names})
    docs = docs.union(docs.limit(1))  # a repeated key takes the other way through the second stage
    for _, function in C.STAGES[:-1]:
        out = function(spark, docs, sf001)
        assert out.columns == docs.columns
        assert all(r[c] == c for r in out.collect() for c in names)


def test_one_row_of_each_group_whatever_its_key(spark, sf001):
    text = " ".join(f"w{i}" for i in range(60))
    other = " ".join(f"v{i}" for i in range(60))
    rows = [(5, text), (5, text), (None, text), (3, text + " end"), (None, other), (None, other), (7, "alone in the world"), (5, "a different text of the same key")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in C.drop_near_duplicates(spark, docs, sf001).collect()), key=str)
    assert got == sorted([(3, text + " end"), (None, other), (7, "alone in the world"), (5, "a different text of the same key")], key=str)
