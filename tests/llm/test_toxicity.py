import itertools
import zlib

import numpy as np
import pytest

from spark_nlops.llm import toxicity as X


@pytest.fixture(scope="module")
def model(spark, request):
    sf = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "toxic").filter(X.crc_remainder("doc_id", 5) != 0)
    return X.train(docs, labels)


def best_path(restorer, text):
    """All paths through a small lattice, one by one."""
    found = []
    for arcs in itertools.product(*restorer.lattice(text)):
        cost, a, b = 0.0, 0, 0
        for letter, price in arcs:
            cost += price
            if letter:
                c = 0 if letter == " " or not letter.isalpha() else X.code_of(letter)
                cost += restorer.costs[(a * X.CODES + b) * X.CODES + c]
                a, b = b, c
        found.append((cost + restorer.costs[(a * X.CODES + b) * X.CODES], "".join(x for x, _ in arcs)))
    return min(found)[1]


def test_viterbi_against_all_paths(model):
    restorer = X.Restorer(model.costs)
    for text in ["1d10t", "i.d.i.o.t", "stuuupid", "a b c", "$c*m", "0", "7r4sh"]:
        assert restorer.decode(text) == best_path(restorer, text)


def test_disguises_are_restored(model):
    restorer = X.Restorer(model.costs)
    for raw, word in [("1d10t", "idiot"), ("stuuuupid", "stupid"), ("i.d.i.o.t", "idiot"), ("tr@sh!!", "trash"), ("m0r0n,", "moron"), ("CLOWN", "clown"), ("w0rthl3ss", "worthless")]:
        assert restorer.words(raw) == [word]
    assert "stupid" in restorer.words("the s t u p i d man")
    for clean in ["the", "Thouatble,", "ciónllci", "größe", "1234", "a", ""]:
        assert restorer.words(clean) == ([clean.lower().strip(",")] if clean else [])


def test_held_out_quality(spark, model):
    sf = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    held = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect() if zlib.crc32(str(r.doc_id).encode()) % 5 == 0}
    got = [(r.score, held[r.doc_id]) for r in X.score(docs, model, keep_text=False).collect() if r.doc_id in held]
    pos, neg = np.array([s for s, y in got if y]), np.array([s for s, y in got if not y])
    assert (pos[:, None] > neg[None]).mean() > 0.8
    assert (neg >= 0.5).mean() < 0.02 and (pos >= 0.5).mean() > 0.7


def test_whole_table(spark, sf001):
    got = X.op1_toxicity(spark, sf001).collect()
    assert len(got) == spark.read.parquet(f"{sf001}/documents.parquet").count()
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)


def test_edges(spark):
    rows = [(i, "good fine words here" if i % 2 else "you bad vile thing") for i in range(60)] + [(None, "you v1le thing"), (100, None), (101, ""), (102, "vile " * 50_000)]
    df = spark.createDataFrame([(*r, "c") for r in rows], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, (i + 1) % 2, 1) for i in range(60)] + [(0, None, 1), (None, 1, 1), (3, 0, 1)], "doc_id long, toxic int, text int")
    model = X.train(df, labels)
    got = {r.doc_id: r.score for r in X.score(df, model).collect()}
    assert got[0] > 0.5 > got[1] and got[None] > 0.5 and got[102] > got[100] == got[101]
    none = X.train(df, labels.limit(0))
    assert {r.score for r in X.score(df, none).collect()} == {0.0}
    assert X.score(df.limit(0), model).count() == 0
    assert X.train(df.limit(0), labels.limit(0)).weights == {}


def test_doubled_letters_and_pieces_are_restored(model):
    restorer = X.Restorer(model.costs)
    for raw, word in [("stuupid", "stupid"), ("idiiot", "idiot"), ("clowwn", "clown"), ("scuum", "scum"), ("stupidd", "stupid")]:
        assert restorer.words(raw) == [word]
    for raw, word in [("i   d   i   o   t", "idiot"), ("s\nt\nu\np\ni\nd", "stupid"), ("s-t-u p-i-d", "stupid"), ("st up id", "stupid")]:
        assert word in restorer.words(f"wonderful {raw} wonderful")
    assert list(X.fragment_runs("the a b cd word i".split())) == ["a b cd"] and list(X.fragment_runs(["a", "b"])) == []
