import zlib

import numpy as np

from spark_nlops.llm import langid as L


def test_held_out_accuracy(spark, sf01):
    rows = {r.doc_id: r for r in spark.read.parquet(f"{sf01}/documents.parquet").collect()}
    got = L.op6_language_id(spark, sf01).collect()
    assert len(got) == len(rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    held = [r for r in got if r.held_out]
    right = [r.lang_pred == rows[r.doc_id].lang for r in held]
    assert np.mean(right) > 0.97
    assert all(0 <= r.score <= 1 for r in got)
    # calibrated: mean confidence is near the accuracy
    assert abs(np.mean([r.score for r in held]) - np.mean(right)) < 0.05


def test_labels_never_reach_held_out_rows(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text", "lang")
    assert L.learnable(docs).filter("crc32(cast(cast(doc_id as string) as binary)) % 4 = 2").count() == 0


def test_edges(spark):
    rows = [(i, t, l, "x") for i, (t, l) in enumerate([("the cat and the dog", "en"), ("le chat et le chien", "fr")] * 40)]
    rows += [(100, None, "en", "x"), (101, "", None, "x"), (102, "123 !?", "fr", "x"), (None, "le chien", "fr", "x"), (103, "the dog " * 200_000, None, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, score string")
    model = L.train(df)
    got = {r.doc_id: r.nlops_language for r in L.predict(df, model).collect()}
    assert [got[i].lang for i in (100, 101, 102)] == ["und"] * 3 and got[100].score == 0.0
    assert got[103].lang == "en" and got[None].lang == "fr" and got[0].lang == "en"
    none = L.train(df.limit(0))
    assert L.predict(df, none).filter("nlops_language.lang <> 'und'").count() == 0
    assert L.predict(df.limit(0), model).count() == 0


def test_elastic_net_gives_zeros():
    fit = L.ProximalFit(2, 0.3, 1.0, 0.5, 0.1)
    fit.learn(np.array([3, 4]), np.array([0.01, 5.0]), 1)
    w = fit.weights()
    assert (w[3] == 0).all() and (w[4] != 0).all()


def test_temperature_sharpens_and_softens():
    labels = np.array([0, 1] * 50)
    logits = np.where(np.arange(2)[None, :] == labels[:, None], 1.0, 0.0)
    assert L.fit_temperature(logits, labels) < 0.2
    wrong = logits.copy()
    wrong[::4] = wrong[::4, ::-1]
    assert L.fit_temperature(wrong * 50, labels) > 5
