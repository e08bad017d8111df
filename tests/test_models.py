"""Models that are asked in ranking, grouping and reduction: callables, a stub endpoint, rules; embedders; the reduction's crowded buckets."""

import http.server
import json
import re
import threading

import pytest
from pyspark.sql import functions as F

from spark_nlops.models.endpoint import EndpointModel
from spark_nlops.models.rules import CallableModel, RuleModel
from spark_nlops.operators import reduce as reduction
from spark_nlops.operators.cluster import nl_classify
from spark_nlops.operators.filter import nl_filter
from spark_nlops.operators.rank import nl_rank
from spark_nlops.operators.reduce import nl_reduce
from spark_nlops.result import SampleSpec
from spark_nlops.stats.hashing import below, uniform
from spark_nlops.template import Template
from spark_nlops.vectors.embed import EndpointEmbedder, HashedNgrams, PrecomputedVectors
from spark_nlops.vectors.index import build_text_index, load_text_index
from spark_nlops.workloads import operators_catalog as oc


def numbers(text):
    return [int(x) for x in re.findall(r"v=(\d+)", text)]


def reply(prompt):
    """What a model that reads numbers would say to each kind of prompt."""
    found = numbers(prompt)
    if "Answer A or B" in prompt:
        return "A" if found[0] > found[1] else "B"
    if "Order the numbers" in prompt:
        return "I think " + " > ".join(str(i) for i in sorted(range(len(found)), key=lambda i: -found[i])) + " and 99"
    if "Answer with one label" in prompt:
        return "  EVEN " if found[0] % 2 == 0 else "Odd"
    if "\n---\n" in prompt or prompt.startswith("sum of"):
        return f"v={sum(numbers(prompt))}"
    return str(found)


@pytest.fixture(scope="module")
def stub():
    class Stub(http.server.BaseHTTPRequestHandler):
        def do_POST(self):
            asked = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
            if "prompts" in asked:
                said = {"answers": [{"text": reply(p), "logp_true": -1.0 / (1 + sum(numbers(p)))} for p in asked["prompts"]]}
            else:
                texts = asked.get("texts") or asked.get("inputs") or asked.get("input")
                said = {"vectors": [[float(len(t)), 1.0, 0.0] for t in texts]}
            body = json.dumps(said).encode()
            self.send_response(200)
            self.send_header("Content-Length", str(len(body)))
            self.end_headers()
            self.wfile.write(body)

        def log_message(self, *_):
            pass

    class Server(http.server.ThreadingHTTPServer):
        request_queue_size = 256

    server = Server(("127.0.0.1", 0), Stub)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    yield f"http://127.0.0.1:{server.server_port}/"
    server.shutdown()


def models(url):
    return {"callable": CallableModel(lambda prompts: [reply(p) for p in prompts]), "endpoint": EndpointModel(url, "stub", batch_size=8, tasks=4)}


@pytest.mark.parametrize("kind", ["callable", "endpoint"])
def test_models_rank_classify_and_reduce(spark, stub, kind):
    model = models(stub)[kind]
    rows = [(i, (i * 37) % 101, "g" + str(i % 2)) for i in range(40)]
    df = spark.createDataFrame(rows, "k long, v long, g string").withColumn("sim", F.col("v") % 7)
    want = [i for i, _, _ in sorted(rows, key=lambda r: -r[1])[:5]]
    for algorithm in ("quickselect", "quadratic", "heap", "listwise"):
        got = nl_rank(df, "v={v}", 5, model, key="k", algorithm=algorithm, window=12).df.orderBy("rank").collect()
        assert [r.k for r in got] == want and [r["rank"] for r in got] == [1, 2, 3, 4, 5], algorithm
    by = nl_rank(df, "v={v}", 2, model, key="k", by=["g"], algorithm="listwise", window=12).df.collect()
    assert sorted((r.g, r["rank"], r.k) for r in by) == [(g, n + 1, i) for g in ("g0", "g1") for n, (i, _, _) in enumerate(sorted((r for r in rows if r[2] == g), key=lambda r: -r[1])[:2])]
    told = {r.k: r.group_label for r in nl_classify(df, "is v={v} even or odd", ["even", "odd"], model, plan="reference").df.collect()}
    assert told == {i: "odd" if v % 2 else "even" for i, v, _ in rows}
    total = nl_reduce(df.withColumn("t", F.concat(F.lit("v="), "v")), "sum of {t}", model, key="k", text="t", fanin=4).df.first().reduced
    assert total == f"v={sum(v for _, v, _ in rows)}"
    if kind == "endpoint":
        scored = nl_rank(df, "v={v}", 5, model, key="k", algorithm="pointwise")
        assert [r.k for r in scored.df.orderBy("rank").collect()] == want and scored.oracle_calls == 40 and "_score" not in scored.df.columns
        again = nl_rank(df, "v={v}", 1, model, key="k", algorithm="rerank", similarity="sim", retrieve=10).df.first()
        assert again.v == max(v for _, v, _ in sorted(rows, key=lambda r: (-(r[1] % 7), r[0]))[:10])


def test_odd_answers(spark):
    df = spark.createDataFrame([([(3, "a"), (4, "b"), (5, None)],), ([],)], "items array<struct<k:int,t:string>>")
    for said, want in (("2, 2 then 7 and 0", [5, 3, 4]), ("no idea", [3, 4, 5]), ([1], [4, 3, 5])):
        model = CallableModel(lambda prompts, said=said: [said for _ in prompts])
        got = model.order(df, Template("{t}"), "items").collect()
        assert [x.k for x in got[0].ordered] == want and got[1].ordered == []
    rule = RuleModel(compare="a.k > b.k")
    assert [x.k for x in rule.order(df, Template("{t}"), "items").first().ordered] == [5, 4, 3]
    unsure = CallableModel(lambda prompts: ["neither" for _ in prompts])
    assert nl_classify(df.select(F.lit("x").alias("t")), "{t}", ["yes", "no"], unsure, plan="reference").df.first().group_label is None


def test_listwise_asks_rules_too(spark):
    df = spark.range(500).select(F.col("id").alias("k"), ((F.col("id") * 7919) % 503).alias("v"))
    rule = RuleModel(compare="a.v > b.v OR (a.v = b.v AND a.k < b.k)")
    got = nl_rank(df, "{v}", 6, rule, key="k", algorithm="listwise")
    assert [r.v for r in got.df.orderBy("rank").collect()] == [502, 501, 500, 499, 498, 497] and got.oracle_calls >= 25


@pytest.mark.parametrize("buckets", [1, 5, 64])
def test_reduction_goes_on_across_buckets(spark, monkeypatch, buckets):
    """More partial texts than are numbered together: neighbours meet in ranges, in order, and the levels end."""
    monkeypatch.setattr(reduction, "TOGETHER", 3)
    df = spark.range(90).select(F.col("id").alias("k"), F.concat(F.lit("w"), F.lpad(F.col("id").cast("string"), 3, "0")).alias("t"))
    join = RuleModel(reducer="array_join(parts, ' ')")
    order = lambda rows: (F.floor(F.col("k") * buckets / 90), F.col("k"))
    got = nl_reduce(df, "{t}", join, key="k", text="t", fanin=2, partitioner=order)
    assert got.df.first().reduced == " ".join(f"w{i:03}" for i in range(90)) and got.df.first().n_sources == 90


def test_answers_of_the_sample_are_used_again(spark):
    """The oracle sees no row twice."""
    seen = []
    df = spark.range(400).select(F.col("id").alias("k"), (F.col("id") / 400).alias("s"), F.concat(F.lit("v="), F.col("id").cast("string")).alias("t"))

    class Counting(RuleModel):
        def label(self, df, template, out="label"):
            seen.append([r.k for r in df.select("k").collect()])
            return super().label(df, template, out)

    got = nl_filter(df, "{t}", Counting(predicate="k % 5 = 0"), proxy=RuleModel(score="s"), key="k", recall=0.9, precision=0.9, sample=SampleSpec(min_rows=100))
    assert {r.k for r in got.df.collect()} == set(range(0, 400, 5))
    asked = [k for part in seen for k in part]
    assert len(asked) == len(set(asked)) == got.oracle_calls and got.plan["reused"] > 0


def test_embedders_without_a_known_width(spark, stub, tmp_path):
    texts = spark.createDataFrame([(i, "x" * i) for i in range(1, 30)], "k long, t string")
    vectors = texts.select("t", F.array(F.col("k").cast("double") - 15, F.lit(2.0), 15 - F.col("k").cast("double")).alias("v"))
    known = PrecomputedVectors(vectors, "t", "v")
    assert {(r.k, tuple(r.vec)) for r in known.embed(texts, "t", "vec").collect()} == {(i, (float(i - 15), 2.0, float(15 - i))) for i in range(1, 30)}
    asked = EndpointEmbedder(stub, "stub", batch_size=4)
    assert {(r.k, tuple(r.vec)) for r in asked.embed(texts, "t", "vec").collect()} == {(i, (float(i), 1.0, 0.0)) for i in range(1, 30)}
    path = str(tmp_path / "index")
    build_text_index(texts, "k", "t", PrecomputedVectors(vectors, "t", "v", of="text"), path)
    index = load_text_index(spark, path)
    assert index.manifest["dim"] == 3 and index.vectors.count() == 29 and index.vectors.select("bucket").distinct().count() > 1


def test_models_in_the_driver_catalog(spark, sf001):
    assert oc.QUERIES["rank_heap"](spark, sf001).count() == 10


def test_hashed_vectors_of_kmeans_rows(spark):
    from spark_nlops.vectors.kmeans import nearest_center

    df = spark.createDataFrame([(1, [0.0, 0.0]), (2, [3.0, 4.0]), (3, None)], "k int, v array<double>")
    got = df.select("k", nearest_center(F.col("v"), [[0.0, 0.0], [3.0, 3.0]]).alias("n")).orderBy("k").collect()
    assert (got[0].n.d, got[0].n.c) == (0.0, 0) and (got[1].n.d, got[1].n.c) == (1.0, 1) and got[2].n.c is None
    assert HashedNgrams().dim == 256


@pytest.mark.parametrize("rate", [-1.0, 0.0, 1e-9, 0.02, 0.5, 1.0, 2.0])
def test_draws_by_digits_are_those_of_uniform(spark, rate):
    """Noise of compared pairs is read off the digits of the hash; every draw is the number's, and null for a null key."""
    df = spark.range(20_000).selectExpr("CASE WHEN id > 0 THEN concat(id, '|', id * 7) END AS k")
    assert df.filter(~(uniform(F.col("k"), 11) < rate).eqNullSafe(below(F.col("k"), 11, rate))).count() == 0
