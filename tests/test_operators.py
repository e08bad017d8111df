"""Joins, rankings, reductions, groups, templates, plans and the surfaces around them."""

import http.server
import json
import threading

import pytest
from pyspark.sql import functions as F

from spark_nlops import session
from spark_nlops.baselines import budget_filter as budget
from spark_nlops.baselines import rewriter
from spark_nlops.functions import text as tx
from spark_nlops.functions.udfs import register_label
from spark_nlops.models.endpoint import EndpointModel
from spark_nlops.models.linear import LinearModel
from spark_nlops.models.memo import PromptMemo
from spark_nlops.models.rules import CallableModel, NoisyModel, RuleModel, VerbalizedConfidence
from spark_nlops.operators import rank
from spark_nlops.operators.cluster import nl_cluster
from spark_nlops.operators.filter import nl_filter
from spark_nlops.operators.join import nl_join
from spark_nlops.operators.project import nl_extract
from spark_nlops.operators.rank import nl_rank
from spark_nlops.operators.reduce import nl_reduce
from spark_nlops.plans import budget as plan_budget
from spark_nlops.plans import cost, explain
from spark_nlops.plans.nodes import NLFilter, NLJoin, NLProject, Source, Where, execute
from spark_nlops.plans.rewrite import rewrite
from spark_nlops.template import Template, TemplateError
from spark_nlops.vectors.embed import HashedNgrams
from spark_nlops.vectors.index import build_text_index, load_text_index
from spark_nlops.vectors.kmeans import vector_kmeans
from spark_nlops.vectors.similarity import similar_pairs
from spark_nlops.workloads import common as w
from spark_nlops.workloads import operators_catalog as oc


def test_templates(spark):
    df = spark.createDataFrame([(1, "x", [1, 2])], "a int, b string, c array<int>")
    t = Template("{b} is {{not}} {a} but {c}; {b}")
    assert t.columns() == ["b", "a", "c"]
    assert df.select(t.bind(df).prompt(df).alias("p")).first().p == "x is {not} 1 but [1,2]; x"
    for bad in ("{nope}", "{b:left}", "a } b", "{}", "{b:up}"):
        with pytest.raises(TemplateError):
            Template(bad).bind(df)
    with pytest.raises(TemplateError):
        Template("{b:left}").bind_pair(df, df)


def top(df, k, seed=0, **more):
    return [(r.k, r.rank) for r in nl_rank(df, "{v}", k, RuleModel(compare="a.v > b.v OR (a.v = b.v AND a.k < b.k)"), key="k", seed=seed, **more).df.orderBy("rank").collect()]


@pytest.mark.parametrize("k", [0, 1, 7, 50, 500])
def test_ranking_algorithms_agree(spark, k):
    rows = [(i, (i * 37) % 53) for i in range(120)]
    df = spark.createDataFrame(rows, "k long, v long").withColumn("sim", (F.col("k") * 11 % 13).cast("double"))
    want = [(i, n + 1) for n, (i, _) in enumerate(sorted(rows, key=lambda r: (-r[1], r[0]))[:k])]
    assert top(df, k) == want and top(df, k, seed=4) == want
    assert top(df, k, pivot="similarity", similarity="sim") == want
    assert top(df, k, algorithm="quadratic") == want
    better = lambda a, b: (a["v"], -a["k"]) > (b["v"], -b["k"])
    assert [(r.k, r.rank) for r in nl_rank(df, "{v}", k, key="k", algorithm="heap", compare=better).df.orderBy("rank").collect()] == want
    if k < 20:
        assert top(df, k, algorithm="listwise", score="v") == want


def test_similarity_pivot_is_lossless(spark, sf01):
    """Correlated, unrelated and adversarial similarity give the same rows; at most one more round for the adversarial one."""
    part = spark.read.parquet(f"{sf01}/part.parquet").select("p_partkey", "p_name", "p_retailprice")
    rounds = {}
    for name, sim in (("good", "p_retailprice"), ("random", "cast(p_partkey * 7919 % 1009 as double)"), ("bad", "-p_retailprice")):
        got = nl_rank(part.withColumn("sim", F.expr(sim)), oc.PRICE, 10, RuleModel(compare=oc.BY_PRICE), key="p_partkey", pivot="similarity", similarity="sim")
        rounds[name] = (got.plan["rounds"], got.oracle_calls, [r.p_partkey for r in got.df.orderBy("rank").collect()])
    assert rounds["good"][2] == rounds["random"][2] == rounds["bad"][2]
    assert rounds["good"][0] <= 3 and rounds["good"][1] <= rounds["random"][1]


def test_ranking_ends_without_a_total_order(spark):
    df = spark.createDataFrame([(i, i % 3) for i in range(30)], "k long, v long")
    cyclic = RuleModel(compare="(a.v + 1) % 3 = b.v")
    assert nl_rank(df, "{v}", 5, cyclic, key="k").df.count() == 5
    noisy = NoisyModel(RuleModel(compare="a.k > b.k"), 0.3, 1, "k")
    assert nl_rank(df, "{v}", 5, noisy, key="k").df.count() == 5


def test_grouped_ranking_keeps_null_groups(spark):
    df = spark.createDataFrame([(i, [None, "x", "y"][i % 3], i) for i in range(30)], "k long, g string, v long")
    got = nl_rank(df, "{v}", 2, RuleModel(compare="a.v > b.v"), key="k", by=["g"]).df.collect()
    assert sorted((str(r.g), r.rank, r.k) for r in got) == [("None", 1, 27), ("None", 2, 24), ("x", 1, 28), ("x", 2, 25), ("y", 1, 29), ("y", 2, 26)]


def test_calls_of_ranking_algorithms(spark):
    df = spark.createDataFrame([(i, (i * 71) % 199) for i in range(199)], "k long, v long")
    rule = RuleModel(compare="a.v > b.v")
    quick = nl_rank(df, "{v}", 10, rule, key="k").oracle_calls
    assert nl_rank(df, "{v}", 10, rule, key="k", algorithm="quadratic").oracle_calls == 199 * 198 // 2 == cost.rank_calls(199, 10, "quadratic")
    heap = nl_rank(df, "{v}", 10, key="k", algorithm="heap", compare=lambda a, b: a["v"] > b["v"]).oracle_calls
    assert quick * 10 < 199 * 198 // 2 and heap * 10 < 199 * 198 // 2


@pytest.mark.parametrize("by, flip", [([], 0.0), (["g"], 0.02), (["g"], 0.4)])
def test_large_groups_are_ranked_without_all_pairs(spark, monkeypatch, by, flip):
    """The wins, ties and noise of all pairs decide, and few pairs are asked; 0.4 leaves out too little, so all are."""
    monkeypatch.setattr(rank, "LARGE", 500)
    df = spark.createDataFrame([(i, None if i < 2500 else "xy"[i % 7 == 0], (i * 7919) % 1999) for i in range(4000)], "k long, g string, v long")
    df = df.unionByName(spark.createDataFrame([(9000 + i, "small", i) for i in range(40)], df.schema))
    model = NoisyModel(RuleModel(compare="a.v > b.v"), flip, 3, "k")
    got = nl_rank(df, "{v}", 5, model, key="k", by=by, algorithm="quadratic")
    whole = rank._wins_order(df.select(*by, F.struct("k", "g", "v").alias("row")), Template("{v}"), model, by, "k", 5).select("row.*", "rank")
    assert sorted(map(str, got.df.collect())) == sorted(map(str, whole.collect()))
    if flip < 0.1:
        assert got.plan["asked_of_large"] < got.oracle_calls / 2
    assert got.oracle_calls == sum(n * (n - 1) // 2 for n in ([4040] if not by else [2500, 1286, 214, 40]))


@pytest.mark.parametrize("fanin", [2, 3, 8])
@pytest.mark.parametrize("parts", [1, 5])
def test_reduction_is_invariant(spark, fanin, parts):
    df = spark.createDataFrame([(i, f"w{i % 9} v{i % 4}") for i in range(100)], "k long, t string").repartition(parts)
    got = nl_reduce(df, "{t}", oc.TERMS, key="k", text="t", fanin=fanin, token_budget=12, provenance=True).df.first()
    assert got.reduced == " ".join(sorted({f"w{i}" for i in range(9)} | {f"v{i}" for i in range(4)})) and got.sources == list(range(100)) and got.n_sources == 100


def test_reduction_order_overflow_and_edges(spark):
    df = spark.createDataFrame([(i, chr(97 + i)) for i in range(20)], "k long, t string")
    want = " | ".join(chr(97 + i) for i in range(20))
    assert nl_reduce(df, "{t}", oc.JOINED, key="k", text="t", pattern="fold").df.first().reduced == want
    assert nl_reduce(df, "{t}", oc.JOINED, key="k", text="t", fanin=3, partitioner=lambda d: (F.lit(0), F.col("k"))).df.first().reduced == want
    assert nl_reduce(df, "{t}", oc.JOINED, key="k", text="t", fanin=3).df.first().reduced != want
    long = spark.createDataFrame([(1, "a " * 50)], "k long, t string")
    assert nl_reduce(long, "{t}", oc.JOINED, key="k", text="t", token_budget=10).df.first().reduced.count("|") == 4
    assert nl_reduce(long, "{t}", oc.JOINED, key="k", text="t", token_budget=10, overflow="truncate").df.first().reduced.count("a") == 10
    with pytest.raises(Exception, match="token budget"):
        nl_reduce(long, "{t}", oc.JOINED, key="k", text="t", token_budget=10, overflow="error").df.collect()
    assert nl_reduce(df.limit(0), "{t}", oc.JOINED, key="k", text="t").df.count() == 0
    assert cost.reduce_calls(64, 8, "tree") == 9 and cost.reduce_calls(5, 2, "fold") == 4


def test_join_plans(spark, sf01):
    docs, items = spark.read.parquet(f"{sf01}/documents.parquet"), spark.read.parquet(f"{sf01}/benchmark.parquet")
    truth = {(r.doc_id, r.item_id) for r in w.contained_pairs(docs, items).collect()}
    costs = {}
    for plan in ("direct", "projected", "auto"):
        got = oc.contains_cascade(spark, sf01, plan=plan)
        out = {(r.doc_id, r.right_item_id) for r in got.df.select("doc_id", "right_item_id").collect()}
        assert len(out & truth) >= 0.9 * len(truth) and len(out & truth) >= 0.9 * len(out)
        costs[plan] = got
    reports = {r.name: r.oracle_calls for r in costs["auto"].plan["reports"]}
    assert reports["projected"] == reports["direct"] + 1000
    assert costs["auto"].plan["plan"] in ("direct", "reference")
    with pytest.raises(ValueError):
        nl_join(docs, items, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", plan="direct")
    assert nl_join(docs.limit(0), items, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id").df.count() == 0


def test_similar_pairs_in_blocks(spark, sf001, monkeypatch):
    from spark_nlops.vectors import similarity

    e = spark.read.parquet(f"{sf001}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    whole = {(r.lk, r.rk, r.rank) for r in similar_pairs(e, e, "vec_id", "v", "vec_id", "v", k=3).collect()}
    monkeypatch.setattr(similarity, "BLOCK_BYTES", 50_000)
    parts = {(r.lk, r.rk, r.rank) for r in similar_pairs(e, e, "vec_id", "v", "vec_id", "v", k=3).collect()}
    assert whole == parts and len(whole) == 1500


def test_groups_discovered_and_given(spark):
    rows = [(i, ["red apple fruit", "green pear fruit", "fast car wheel", "slow truck wheel"][i % 4]) for i in range(80)]
    df = spark.createDataFrame(rows, "k long, t string")
    oracle = RuleModel(classifier={"fruit": "cast(contains(t, 'fruit') as double)", "wheel": "cast(contains(t, 'wheel') as double)"})
    given = nl_cluster(df, "{t}", 2, key="k", projector=RuleModel(project="t"), embedder=HashedNgrams(), reducer=oc.TERMS, oracle=oracle, labels=["fruit", "wheel"])
    assert {(r.t.split()[-1], r.group_label) for r in given.df.collect()} == {("fruit", "fruit"), ("wheel", "wheel")}
    names = RuleModel(project="element_at(split(t, ' '), -1)")
    label = RuleModel(reducer="parts[0]")
    found = nl_cluster(df, "{t}", 2, key="k", projector=names, embedder=HashedNgrams(), reducer=label, oracle=oracle)
    assert found.plan["labels"] == ["fruit", "wheel"] and found.df.filter("group_label <> element_at(split(t, ' '), -1)").count() == 0
    many, centers = vector_kmeans(HashedNgrams(1, 16).embed(df, "t", "v"), "k", "v", 10)
    assert len(centers) == 4 and many.select("cluster").distinct().count() == 4


def test_extraction_is_verbatim(spark):
    df = spark.createDataFrame([(1, "mail a@b.org and a@b.org or c@d.net"), (2, "none"), (3, None)], "k long, t string")
    got = {r.k: r.f for r in nl_extract(df, "{t}", "f", text="t", pattern=tx.EMAIL).collect()}
    assert [(s.start, s.end, s.text) for s in got[1]] == [(5, 12, "a@b.org"), (17, 24, "a@b.org"), (28, 35, "c@d.net")] and got[2] == []
    said = CallableModel(lambda prompts: ["and\nnowhere"] * len(prompts))
    assert [s.text for s in nl_extract(df, "{t}", "f", text="t", model=said).collect()[0].f] == ["and"]


def test_text_functions(spark):
    html = "<p>a &lt; b</p><script>x<y</script><!-- c --><style>p{}</style>\n<b>c&amp;d</b>"
    df = spark.createDataFrame([(html, " ".join(f"w{i}" for i in range(25)))], "h string, t string")
    assert df.select(tx.html_to_text(F.col("h")).alias("x")).first().x == "a < b c&d"
    chunks = [r.chunk for r in tx.chunk(df, "t", 10, 4).collect()]
    assert len(chunks) == 4 and chunks[1].split()[:4] == chunks[0].split()[-4:] and chunks[-1].split()[-1] == "w24"


def test_endpoint_batches_retries_and_scores(spark):
    seen = []

    class Stub(http.server.BaseHTTPRequestHandler):
        failed = False

        def do_POST(self):  # noqa: N802
            body = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
            if not Stub.failed:
                Stub.failed = True
                self.send_error(503)
                return
            seen.append(len(body["prompts"]))
            out = {"answers": [{"text": f"because\n{'odd' in p}", "logp_true": -0.1 if "odd" in p else -3.0} for p in body["prompts"]]}
            data = json.dumps(out).encode()
            self.send_response(200)
            self.send_header("Content-Length", str(len(data)))
            self.end_headers()
            self.wfile.write(data)

        def log_message(self, *args):
            pass

    server = http.server.ThreadingHTTPServer(("127.0.0.1", 0), Stub)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    model = EndpointModel(f"http://127.0.0.1:{server.server_port}/", "stub", batch_size=16, demos=(("1", "true"),), reasoning=True)
    df = spark.createDataFrame([(i, "odd" if i % 2 else "even") for i in range(100)] + [(100, None)], "k long, t string")
    got = model.label(df, Template("{t}"), "y").collect()
    assert sum(bool(r.y) for r in got) == 50 and got[-1].y is None and max(seen) <= 16
    assert model.score(df, Template("{t}"), "p").filter("p > 0.5").count() == 50
    assert model.answer(df, Template("{t}"), "a").first().a.reason == "because"
    server.shutdown()


def test_memo_asks_distinct_prompts_once(spark, tmp_path):
    df = spark.createDataFrame([(i, f"t{i % 5}") for i in range(50)] + [(99, None)], "k long, t string")
    memo = PromptMemo(RuleModel(predicate="t IN ('t1', 't2')"), str(tmp_path / "memo"))
    assert nl_filter(df, "{t}", memo, plan="reference").df.count() == 20 and memo.asked == 5
    assert nl_filter(df, "{t} ", memo, plan="reference").df.count() == 20 and memo.asked == 5
    again = PromptMemo(RuleModel(predicate="false"), str(tmp_path / "memo"))
    assert nl_filter(df, "{t}", again, plan="reference").df.count() == 20 and again.asked == 0


def test_linear_and_stated_scores(spark):
    df = spark.createDataFrame([(i, "good fine" if i % 2 else "bad poor", i % 2) for i in range(100)], "k long, t string, y int")
    linear = LinearModel(df, "t", "y")
    assert linear.label(df, Template("{t}")).filter("label <> (y = 1)").count() == 0
    stated = VerbalizedConfidence(RuleModel(project="concat(cast(y * 80 + 10 as string), ' percent')"))
    assert {r.score for r in stated.score(df, Template("{t}")).collect()} == {0.1, 0.9}


def test_rewrites_keep_results_and_save_calls(spark):
    df = spark.createDataFrame([(i, i % 5, f"t{i}") for i in range(50)], "k long, a long, t string")
    asked = []

    def ask(name, rule):
        return lambda d: (asked.append((name, d.count())), d.filter(rule))[1]

    costly = NLFilter(Source(df), Template("{t}"), ask("costly", "k % 2 = 0"), cost=10, selectivity=0.5)
    cheap = NLFilter(costly, Template("{k}"), ask("cheap", "k < 20"), cost=1, selectivity=0.4)
    plan = Where(NLProject(cheap, Template("{t}"), "p", lambda d: d.withColumn("p", F.lit(1))), "a = 1", ("a",))
    before = sorted(r.k for r in execute(plan).collect())
    first = list(asked)
    asked.clear()
    better = rewrite(plan)
    assert sorted(r.k for r in execute(better).collect()) == before
    assert dict(asked)["costly"] < dict(first)["costly"] and dict(asked)["cheap"] == 10
    assert better.describe() == "NLProject p" and "Where a = 1" in explain.explain_program(plan)
    other = spark.createDataFrame([(1,)], "z long")
    joined = NLJoin(Source(df), Source(other), Template("{a:left} {z:right}"), lambda l, r: l.crossJoin(r), left_only=("a", "k", "t"))
    pushed = rewrite(Where(joined, "a = 1", ("a",)))
    assert isinstance(pushed, NLJoin) and isinstance(pushed.left, Where)
    assert isinstance(rewrite(Where(joined, "z = 1", ("z",))), Where)


def test_program_budget():
    with plan_budget.guarantee(4, recall=0.9, delta=0.2) as own:
        assert own.delta == pytest.approx(0.05) and own.recall**4 == pytest.approx(0.9) and plan_budget.current() is own
    assert plan_budget.current() is None


def test_baselines(spark, sf01):
    docs = HashedNgrams(1, 32).embed(spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", "text"), "text", "v")
    got = budget.budget_filter(docs, w.JUNK, w.junk_oracle(), key="doc_id", vec="v", budget=120, batch=40)
    assert got.oracle_calls <= 120 and got.df.count() > 0
    runs, made = rewriter.mean_of_successes(lambda seed: rewriter.NLResult(None, {}, {"success": rewriter.succeeds(seed)}), wanted=20, most=60)
    assert len(runs) == 20 and 22 <= made <= 45


def test_session_surface_and_index(spark, sf001, tmp_path):
    session.enable(spark)
    docs = spark.read.parquet(f"{sf001}/documents.parquet")
    assert docs.nl_filter(w.JUNK, w.junk_oracle(), plan="reference").df.count() == docs.filter(oc.JUNK_SQL.replace(", 'g')", ")")).count()
    register_label(spark, "nl_label", lambda prompts: ["a" in p for p in prompts])
    assert spark.sql("SELECT nl_label(x) AS y FROM VALUES ('ab'), ('cd'), (null) t(x)").collect() == [(True,), (False,), (None,)]
    assert spark.sql("SELECT * FROM nl_snippets('to a@b.org now', 'email')").collect() == [(3, 10, "a@b.org")]
    assert spark.sql("SELECT nl_summary(x) AS y FROM VALUES ('b a'), ('A c') t(x)").first().y == "a b c"
    path = str(tmp_path / "index")
    build_text_index(docs, "doc_id", "text", HashedNgrams(), path)
    index = load_text_index(spark, path)
    assert index.matches(docs) and not index.matches(docs.limit(3)) and index.vectors.count() == docs.count()
    assert spark.read.format("nlops_index").option("path", path).load().count() == docs.count()
    some = index.vectors.select("vec").first().vec
    assert 0 < index.probe(list(some)).count() <= docs.count()
    assert "Scan" in explain.physical_plan(docs.select("doc_id"))


def test_pushdown_reaches_the_scan(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    plan = explain.physical_plan(nl_filter(docs.select("doc_id", "text", "lang").filter("lang = 'fr'"), w.JUNK, w.junk_oracle(), plan="reference").df.select("doc_id"))
    assert "EqualTo(lang,fr)" in plan and "source" not in plan.split("ReadSchema")[1].splitlines()[0] and "Python" not in plan
