"""Experiment workloads: methods side by side, parameter sweeps, programs and streams."""

from __future__ import annotations

import hashlib
import time
import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import measures
from ..baselines import budget_filter as budget
from ..baselines import factcheck, rewriter
from ..models.rules import CallableModel, NoisyModel, RuleModel
from ..operators.cluster import discover_groups, nl_classify
from ..operators.filter import nl_filter
from ..operators.join import nl_join
from ..operators.project import nl_project
from ..operators.rank import nl_rank
from ..operators.reduce import nl_reduce
from ..operators.search import embedded, nl_similar_join, with_similarity
from ..result import SampleSpec
from ..sources.tables import read_table
from ..staging import shared_folder, staged
from ..stats import cuts
from ..stats.hashing import md5_int
from ..streaming import streams
from ..template import Template
from ..vectors.embed import HashedNgrams
from ..vectors.similarity import similar_pairs
from . import common as w
from . import operators_catalog as oc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def table(s, rows, schema) -> DataFrame:
    return s.createDataFrame(rows, schema)


# --- W1: claim verification ------------------------------------------------------------
def all_claims(s, d) -> DataFrame:
    """Benchmark items, and the same items with their words in hash order as claims without support."""
    items = oc.claims(s, d)
    mixed = F.array_join(F.transform(F.array_sort(F.transform(F.split("claim", r"\s+"), lambda x, i: F.struct(F.md5(F.concat(x, i.cast("string"))).alias("h"), x.alias("x")))), lambda p: p["x"]), " ")
    return items.unionByName(items.select((F.col("claim_id") + 1_000_000).alias("claim_id"), mixed.alias("claim")))


def claim_truth(s, d, claims) -> DataFrame:
    supported = claims.join(oc.docs(s, d, "text"), F.expr("contains(text, claim)"), "left_semi").select("claim_id").withColumn("truth", F.lit(True))
    return claims.select("claim_id").join(supported, "claim_id", "left").select("claim_id", F.coalesce("truth", F.lit(False)).alias("truth"))


@query("w1_factcheck_methods")
def _(s, d):
    """Accuracy and oracle calls of each program; row-wise and hand-written programs judge every claim."""
    claims, corpus = staged(all_claims(s, d), "claims"), oc.docs(s, d, "doc_id", "text")
    truth, n = staged(claim_truth(s, d, claims), "truth"), claims.count()
    args = (claims, corpus, oc.UNIGRAMS, oc.SUPPORTED, oc.FACT_K)
    evidence = HashedNgrams(1, 64).embed(factcheck.retrieved(claims, corpus, oc.UNIGRAMS, oc.FACT_K), "context", "v")
    plain = factcheck.operator_program(*args)
    fast = factcheck.operator_program(*args, proxy=oc.SUPPORTED, recall=0.9, precision=0.9)
    spent = budget.budget_filter(evidence, factcheck.VERDICT, oc.SUPPORTED, key="claim_id", vec="v", budget=max(20, n // 4), batch=10)
    runs = [
        ("handwritten", factcheck.handwritten_pipeline(*args), 2 * n), ("rowwise", factcheck.rowwise_program(*args), 2 * n),
        ("budgeted", spent.df, n + spent.oracle_calls), ("operators_reference", plain.df, n + plain.oracle_calls), ("operators_cascade", fast.df, n + fast.oracle_calls),
    ]
    rows = []
    for name, out, calls in runs:
        pred = truth.select("claim_id").join(out.select("claim_id").distinct().withColumn("p", F.lit(True)), "claim_id", "left").fillna({"p": False})
        rows.append((name, round(measures.accuracy(pred, truth, "claim_id", "p", "truth").first()["accuracy"], 6), calls, round(measures.extrapolate(calls), 3)))
    return table(s, rows, "method string, accuracy double, calls long, modelled_sec double")


@query("w1_filter_target_sweep")
def _(s, d):
    """Oracle calls, accepted share and accuracy of the junk filter as the target moves."""
    gold = staged(nl_filter(oc.docs(s, d, "doc_id", "text"), w.JUNK, w.junk_oracle(), plan="reference").df.select("doc_id"), "gold")
    rows = []
    for target in (0.5, 0.7, 0.9, 0.95):
        got = oc.junk_cascade(s, d, bound="exact", recall=target, precision=target)
        r = measures.set_precision_recall(got.df, gold, ["doc_id"]).first()
        rows.append((target, got.oracle_calls, r["recall"], r["precision"]))
    return table(s, rows, "target double, oracle_calls long, recall double, precision double")


# --- W2: label join ----------------------------------------------------------------------
@query("w2_label_join_methods")
def _(s, d):
    left, right = oc.docs(s, d, "doc_id", "text"), read_table(s, d, "benchmark")
    truth = staged(w.contained_pairs(left, right), "truth")
    nested = left.count() * right.count()
    vectors = staged(embedded(left, "text", "doc_id", oc.UNIGRAMS), "vectors")  # once for search and blocking
    ranked_search = oc.ranked_items(s, d, vectors=vectors)
    got = oc.contains_cascade(s, d)
    matched = staged(got.df.select("doc_id", F.col("right_item_id").alias("item_id")), "matches")
    block = rewriter.mean_of_successes(lambda seed: rewriter.blocking_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", embedder=oc.UNIGRAMS, budget=5 * left.count(), seed=seed, vectors=vectors))
    blocked = block[0][0].df.select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"))
    rows = []
    learned = budget.budget_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", embedder=HashedNgrams(1, 64), budget=300)
    learned_pairs = learned.df.select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"))
    # list-wise order of each document's matches by similarity of the strong vectors
    held = staged(left.join(matched.select("doc_id").distinct(), "doc_id", "left_semi"), "held")  # only these have matches to order
    near = similar_pairs(oc.TRIGRAMS.embed(held, "text", "v"), oc.TRIGRAMS.embed(right, "text", "v"), "doc_id", "v", "item_id", "v", least=0.0)
    listed = staged(matched.join(near.select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"), "sim"), ["doc_id", "item_id"]), "listed")
    ordered = nl_rank(listed, "{sim} fits best", 10, key="item_id", by=["doc_id"], algorithm="listwise", score="sim")
    runs = (
        ("search_only", ranked_search, 0), ("nested_loop", truth, nested), ("budgeted", learned_pairs, learned.oracle_calls), ("rewriter_blocking", blocked, block[0][0].calls["oracle"]),
        ("cascade", matched, got.oracle_calls), ("cascade_listwise_rank", ordered.df.select("doc_id", "item_id", "rank"), got.oracle_calls + ordered.oracle_calls),
    )
    for name, out, calls in runs:
        from pyspark.sql import Window

        ranked = out if "rank" in out.columns else out.withColumn("rank", F.row_number().over(Window.partitionBy("doc_id").orderBy("item_id")))
        ranked = staged(ranked, "ranked")
        p5, p10 = (measures.rank_precision(ranked, truth, "doc_id", "item_id", k).first()["rank_precision"] for k in (5, 10))
        rows.append((name, p5, p10, calls, round(measures.extrapolate(calls), 3)))
    return table(s, rows, "method string, rp5 double, rp10 double, calls long, modelled_sec double")


@query("w2_join_plans")
def _(s, d):
    """Each plan by itself, and the choice between them, under a weak and a strong embedder: calls, recall and precision.

    The direct plan embeds whole documents; the projected one embeds what a model
    names in them, one call for each document, which is nearer to the items.
    """
    truth = staged(w.contained_pairs(oc.docs(s, d), read_table(s, d, "benchmark")), "truth")
    projector, pairs = oc.passage_projector(s, d), oc.docs(s, d).count() * read_table(s, d, "benchmark").count()
    rows = []
    for name, embedder in (("unigrams", oc.UNIGRAMS), ("trigrams", oc.TRIGRAMS)):
        for plan in ("direct", "projected", "auto"):
            got = oc.contains_cascade(s, d, plan=plan, embedder=embedder, projector=projector)
            r = measures.set_precision_recall(got.df.select("doc_id", F.col("right_item_id").alias("item_id")), truth, ["doc_id", "item_id"]).first()
            rows.append((name, plan, got.plan["plan"], got.oracle_calls, round(pairs / max(got.oracle_calls, 1), 6), r["recall"], r["precision"]))
    return table(s, rows, "embedder string, plan string, ran string, oracle_calls long, fewer_by double, recall double, precision double")


@query("w2_sample_of_500")
def _(s, d):
    """The same join with another embedder and samples of 500 and 4 000 pairs."""
    rows = []
    for size in (500, 4000):
        got = oc.contains_cascade(s, d, embedder=HashedNgrams(2, 512), spec=SampleSpec(min_rows=size, weight_power=16.0, seed=5))
        truth = w.contained_pairs(oc.docs(s, d), read_table(s, d, "benchmark"))
        r = measures.set_precision_recall(got.df.select("doc_id", F.col("right_item_id").alias("item_id")), truth, ["doc_id", "item_id"]).first()
        rows.append((size, got.plan["plan"], got.oracle_calls, r["recall"], r["precision"]))
    return table(s, rows, "sample_rows int, plan string, oracle_calls long, recall double, precision double")


@query("similar_pairs_lsh_recall", f"SELECT count(*) AS n_pairs, true AS recall_met FROM ({oc.sims_sql('documents', 'doc_id', 'text', 'benchmark', 'item_id', 'text', HashedNgrams(1, 64))}) WHERE sim >= 0.85")
def _(s, d):
    """All pairs of at least 0.85, and whether bucketed pairs find nine of ten of them and nothing else."""
    from ..vectors.similarity import bucketed_pairs

    small = HashedNgrams(1, 64)
    left, right = staged(small.embed(oc.docs(s, d, "doc_id", "text"), "text", "v"), "left"), staged(small.embed(read_table(s, d, "benchmark"), "text", "v"), "right")
    exact = staged(similar_pairs(left, right, "doc_id", "v", "item_id", "v", least=0.85), "exact").select("lk", "rk")
    found = bucketed_pairs(left, right, "doc_id", "v", "item_id", "v", least=0.85, dim=64)
    r = measures.set_precision_recall(found, exact, ["lk", "rk"]).first()
    return table(s, [(exact.count(), bool(r["recall"] >= 0.9 and r["precision"] == 1.0))], "n_pairs long, recall_met boolean")


@query("w2_direct_and_projected_agree", oc.met_sql(oc.PAIRS_SQL))
def _(s, d):
    """The worse of both plans, with a projector that names the passage, against the truth."""
    truth = staged(w.contained_pairs(oc.docs(s, d), read_table(s, d, "benchmark")), "truth")
    projector = oc.passage_projector(s, d)
    found = [oc.contains_cascade(s, d, plan=plan, projector=projector).df.select("doc_id", F.col("right_item_id").alias("item_id")) for plan in ("direct", "projected")]
    told = [oc.met(s, out, truth, ["doc_id", "item_id"]) for out in found]
    return told[0].unionByName(told[1]).groupBy("metric").agg(F.min("n_truth").alias("n_truth"), F.min("met").alias("met"))


# --- W3: ranking -------------------------------------------------------------------------
TRIALS = 20


def flipped(pair: tuple[str, str], seed: int, rate: float) -> bool:
    """The seeded draw of ``NoisyModel`` in Python, for heaps."""
    low, high = sorted(pair)
    return low != high and int(hashlib.md5(f"{seed}:{low}|{high}".encode()).hexdigest()[:8], 16) / 4294967296.0 < rate


@query("w3_price_ranking_algorithms")
def _(s, d):
    """Eight algorithms under noisy comparisons and scores, twenty seeded trials at once: mean quality and calls of a trial.

    Trials are groups of one ranking, with noise by trial and row.  Search asks nothing
    and has no noise; quadratic ranking, of all pairs, runs in one trial.
    """
    part = read_table(s, d, "part", ["p_partkey", "p_name", "p_retailprice"])
    told = staged(with_similarity(part, "p_name", oc.QUESTION, oc.UNIGRAMS), "part")  # once for all trials
    many = told.crossJoin(s.range(TRIALS).select(F.col("id").cast("int").alias("trial"))).withColumn("tk", F.col("trial") * F.lit(10**10) + F.col("p_partkey"))
    # a score is wrong in one row of ten, and then says any price up to twice the true one
    said = F.when(oc.sampling.uniform(F.col("tk"), 11) < 0.1, 2 * F.col("p_retailprice") * oc.sampling.uniform(F.col("tk"), 12)).otherwise(F.col("p_retailprice"))
    many = staged(many.withColumn("said", said), "trials")
    one = many.filter("trial = 0")
    top = nl_rank(part, oc.PRICE, oc.K, key="p_partkey", algorithm="pointwise", score="p_retailprice").df
    gains = staged(many.select("trial", "tk", "p_partkey").join(top.select("p_partkey", (F.lit(oc.K + 1) - F.col("rank")).cast("double").alias("gain")), "p_partkey"), "gains")
    noisy = NoisyModel(RuleModel(compare=oc.BY_PRICE), 0.02, 11, "tk")
    by_noise = lambda a, b: oc.by_price(a, b) != flipped((str(a["tk"]), str(b["tk"])), 11, 0.02)
    grouped = {"key": "tk", "by": ["trial"]}
    runs = {
        "search": (nl_rank(one, oc.PRICE, oc.K, algorithm="search", similarity="sim", **grouped), 1),
        "pointwise": (nl_rank(many, oc.PRICE, oc.K, algorithm="pointwise", score="said", **grouped), TRIALS),
        "listwise": (nl_rank(many, oc.PRICE, oc.K, algorithm="listwise", score="said", **grouped), TRIALS),
        "rerank": (nl_rank(many, oc.PRICE, oc.K, algorithm="rerank", similarity="sim", score="said", retrieve=100, **grouped), TRIALS),
        "quadratic": (nl_rank(one, oc.PRICE, oc.K, noisy, algorithm="quadratic", **grouped), 1),
        "heap": (nl_rank(many, oc.PRICE, oc.K, algorithm="heap", compare=by_noise, **grouped), TRIALS),
        "quickselect": (nl_rank(many, oc.PRICE, oc.K, noisy, **grouped), TRIALS),
        "quickselect_similarity": (nl_rank(many, oc.PRICE, oc.K, noisy, pivot="similarity", similarity="sim", **grouped), TRIALS),
    }
    rows = []
    for name, (got, n) in runs.items():
        due = gains if n > 1 else gains.filter("trial = 0")
        quality = measures.ndcg(staged(got.df.select("trial", "tk", "rank"), "got"), due, "trial", "tk", "gain", oc.K).first()
        rows.append((name, n, round(quality["ndcg"], 6), got.oracle_calls / n, round(measures.extrapolate(got.oracle_calls / n), 3)))
    return table(s, rows, "algorithm string, trials int, ndcg10 double, oracle_calls double, modelled_sec double")


@query("w3_relevance_ranking")
def _(s, d):
    """Each benchmark item as a query over the hundred documents nearest to it: eight methods, quality by containment.

    The model doesn't see whether an item is contained: it sees the share of the item's
    words that a document has, and errs in a share of its comparisons and scores.
    """
    items, corpus = read_table(s, d, "benchmark"), oc.docs(s, d, "doc_id", "text")
    found = nl_similar_join(items, corpus, "text", "text", 100, left_key="item_id", right_key="doc_id", embedder=oc.UNIGRAMS)
    pairs = staged(found.filter("right_key IS NOT NULL").select(F.col("left_key").alias("item_id"), F.col("right_key").alias("doc_id"), "sim"), "found")
    gains = staged(w.contained_pairs(corpus, items).withColumn("gain", F.lit(1.0)), "gains")
    words = lambda c: F.array_distinct(F.filter(F.split(F.lower(F.col(c)), r"\s+"), lambda x: x != ""))
    both = pairs.join(items.select("item_id", F.col("text").alias("claim")), "item_id").join(corpus, "doc_id")
    overlap = F.size(F.array_intersect(words("text"), words("claim"))) / F.greatest(F.size(words("claim")), F.lit(1))
    key = F.col("item_id") * F.lit(10**10) + F.col("doc_id")
    both = both.withColumns({"pk": key, "seen": F.round(overlap, 6)})
    said = F.when(oc.sampling.uniform(F.col("pk"), 13) < 0.1, oc.sampling.uniform(F.col("pk"), 14)).otherwise(F.col("seen"))
    both = staged(both.withColumn("said", said).select("item_id", "doc_id", "pk", "sim", "seen", "said"), "both")
    noisy = NoisyModel(RuleModel(compare="a.seen > b.seen OR (a.seen = b.seen AND a.pk < b.pk)"), 0.02, 15, "pk")
    by_noise = lambda a, b: ((a["seen"], -a["pk"]) > (b["seen"], -b["pk"])) != flipped((str(a["pk"]), str(b["pk"])), 15, 0.02)
    grouped = {"key": "pk", "by": ["item_id"]}
    asks = "{seen} of the claim is answered"
    runs = {
        "search": nl_rank(both, asks, 10, algorithm="search", similarity="sim", **grouped),
        "pointwise": nl_rank(both, asks, 10, algorithm="pointwise", score="said", **grouped),
        "listwise": nl_rank(both, asks, 10, algorithm="listwise", score="said", **grouped),
        "rerank": nl_rank(both, asks, 10, algorithm="rerank", similarity="sim", score="said", retrieve=50, **grouped),
        "quadratic": nl_rank(both, asks, 10, noisy, algorithm="quadratic", **grouped),
        "heap": nl_rank(both, asks, 10, algorithm="heap", compare=by_noise, **grouped),
        "quickselect": nl_rank(both, asks, 10, noisy, **grouped),
        "quickselect_similarity": nl_rank(both, asks, 10, noisy, pivot="similarity", similarity="sim", **grouped),
    }
    rows = []
    for name, got in runs.items():
        quality = measures.ndcg(staged(got.df.select("item_id", "doc_id", "rank"), "got"), gains, "item_id", "doc_id", "gain", 10).first()["ndcg"]
        rows.append((name, round(quality, 6), got.oracle_calls, round(measures.extrapolate(got.oracle_calls), 3)))
    return table(s, rows, "method string, ndcg10 double, calls long, modelled_sec double")


# --- W4: topics ---------------------------------------------------------------------------
@query("w4_topic_discovery")
def _(s, d):
    """Languages found from candidate labels for three numbers of groups, then assigned by reference, proxy only and cascades; seconds are wall time of discovery or planning."""
    df = oc.docs(s, d, "doc_id", "text", "lang")
    namer = RuleModel(project="concat_ws(' ', slice(filter(split(lower(text), ' '), x -> length(x) <= 3), 1, 12))", model_id="short words")
    rows = []
    for c in (3, 4, 5):
        (clustered, _labels, notes), took = measures.timed(lambda c=c: discover_groups(df, "a topic for {text}", c, key="doc_id", projector=namer, embedder=oc.UNIGRAMS, reducer=oc.TERMS))
        purity = clustered.groupBy("cluster", "lang").count().groupBy("cluster").agg(F.max("count").alias("most"), F.sum("count").alias("n")).agg((F.sum("most") / F.sum("n")).alias("p")).first()["p"]
        rows.append((f"discovery_purity_{c}", purity, notes.oracle_calls, took))
    gold = staged(nl_classify(df, oc.LANGUAGE, list(oc.STOPS), oc.language_oracle(), plan="reference").df, "gold").withColumnRenamed("group_label", "truth")
    for name, more in (("proxy_only", {"plan": "proxy_only"}), *((f"cascade_{a}", {"accuracy": a}) for a in (0.7, 0.8, 0.9))):
        got, took = measures.timed(lambda more=more: nl_classify(df, oc.LANGUAGE, list(oc.STOPS), oc.language_oracle(), key="doc_id", text="text", embedder=oc.UNIGRAMS, centers=oc.label_centers(), sample=SampleSpec(min_rows=100), **more))
        rows.append((name, measures.accuracy(got.df, gold, "doc_id", "group_label", "truth").first()["accuracy"], got.oracle_calls, took))
    rows.append(("reference", 1.0, df.count(), 0.0))
    return table(s, [(n, round(float(a), 6), round(measures.relative_accuracy(float(a), 1.0), 6), int(c), round(t, 3), round(measures.extrapolate(int(c)), 3)) for n, a, c, t in rows], "method string, accuracy double, relative_accuracy double, oracle_calls long, planning_sec double, modelled_sec double")


@query("w1_batching_times")
def _(s, d):
    """The claim filter with a served model of a fixed answering time, asked one prompt at a time and in batches: mean wall time of three runs."""
    claims = staged(all_claims(s, d), "claims")

    def served(prompts: list[str]) -> list[bool]:
        time.sleep(0.002 + 0.0001 * len(prompts))
        return [len(p) % 2 == 0 for p in prompts]

    rows = []
    for size in (1, 64):
        model = CallableModel(served, batch_size=size)
        n, took = measures.timed(lambda model=model: nl_filter(claims, "{claim} is supported", model, plan="reference").df.count(), runs=3)
        rows.append((size, n, -(-claims.count() // size), round(took, 3)))
    return table(s, rows, "batch_size int, accepted long, least_requests long, mean_sec double")


@query("m_success_rate", "SELECT avg(((('0x' || substr(md5('plan:' || doc_id::VARCHAR), 1, 8))::BIGINT / 4294967296.0::DOUBLE) >= 1.0 / 3)::INT)::DOUBLE AS success_rate, count(*) AS n_runs FROM documents")
def _(s, d):
    """Share of the rewriter's runs that end with a valid plan, one run for each document, whose key is the seed."""
    return measures.success_rate(oc.docs(s, d, "doc_id").select(rewriter.success(F.col("doc_id")).alias("success")))


@query("w4_useless_proxy", "SELECT vec_id, label::VARCHAR AS group_label FROM embeddings")
def _(s, d):
    """Vectors that say nothing about the label: the cascade must fall back to the oracle and stay exact."""
    e = read_table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"), F.col("label").cast("string").alias("truth"))
    names = [r["truth"] for r in e.select("truth").distinct().orderBy("truth").collect()]
    oracle = RuleModel(classifier={k: f"cast(truth = '{k}' as double)" for k in names})
    means = {r["truth"]: list(r["m"]) for r in e.select("truth", F.posexplode("v").alias("p", "x")).groupBy("truth", "p").agg(F.avg("x").alias("a")).groupBy("truth").agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "a"))), lambda t: t["a"]).alias("m")).collect()}
    got = nl_classify(e, "the label of {truth}", names, oracle, key="vec_id", vec="v", centers=means, accuracy=0.9, sample=SampleSpec(min_rows=200))
    return got.df.select("vec_id", "group_label")


# --- W5: guarantees ----------------------------------------------------------------------
PROXIES = {"strong": w.STRONG, "weak": w.WEAK, "useless": "cast(conv(substring(md5(text), 1, 8), 16, 10) as double) / 4294967296.0D"}


class JunkTrials:
    """Many planned cascades over one scored table: the engine's samples, weights and cuts, each trial with its own seed.

    All seeds' samples are drawn in one job and are all that reaches the driver (about
    trials times sample size rows); all cuts are judged in another, over the whole table.
    """

    def __init__(self, s, d, expr: str, trials: int, min_rows: int = 300) -> None:
        t = Template(w.JUNK)
        scored = oc.calibrate.quantile_scale(w.junk_proxy(expr).score(oc.docs(s, d, "doc_id", "text"), t, "score").filter("score IS NOT NULL"), "score", "q")
        self.rows = staged(w.junk_oracle().label(scored, t, "y").select("doc_id", "q", "y"), "trials")
        spec = SampleSpec(min_rows=min_rows)
        n, total = self.rows.agg(F.count("*"), F.sum(F.pow("q", F.lit(spec.weight_power)))).first()
        pi = oc.sampling.inclusion_probability(F.col("q"), float(total or 0), n, spec.size(n), spec)
        seeds = s.range(trials).select(F.col("id").alias("seed"))
        u = md5_int(F.concat(F.col("seed").cast("string"), F.lit(":"), F.col("doc_id").cast("string"))) / F.lit(4294967296.0)
        drawn = self.rows.withColumn("pi", pi).crossJoin(F.broadcast(seeds)).filter(u < F.col("pi")).select("seed", "doc_id", "q", "y", "pi").toPandas().sort_values(["seed", "doc_id"])
        self.spark, self.samples = s, {int(k): cuts.Sample(g["q"].to_numpy(float), g["y"].to_numpy(float), 1 / g["pi"].to_numpy(float)) for k, g in drawn.groupby("seed")}

    def judged(self, settings: list[tuple]) -> dict[tuple, list[tuple[float, float, int]]]:
        """For settings (recall and precision target, delta, bound): each trial's recall, precision and oracle calls."""
        runs = []
        for i, (target, delta, bound) in enumerate(settings):
            for seed, sample in self.samples.items():
                runs.append((i, seed, *(float(x) for x in cuts.two_cuts(sample, target, target, delta, bound)), len(sample)))
        plans = self.spark.createDataFrame(runs, "setting int, seed int, lo double, hi double, sampled long")
        accept, ask = F.col("q") >= F.col("hi"), (F.col("q") < F.col("hi")) & (F.col("q") >= F.col("lo"))
        out = accept | (ask & F.col("y"))
        count = lambda c: F.sum(c.cast("long"))
        got = self.rows.crossJoin(F.broadcast(plans)).groupBy("setting", "seed", "sampled").agg(count(out & F.col("y")).alias("hits"), count(out).alias("n_out"), count(F.col("y")).alias("n_gold"), count(ask).alias("asked"))
        found: dict[tuple, list] = {x: [] for x in settings}
        for r in got.collect():  # one row for each trial
            found[settings[r["setting"]]].append((r["hits"] / max(r["n_gold"], 1), r["hits"] / r["n_out"] if r["n_out"] else 1.0, r["sampled"] + r["asked"]))
        return found


@query("w5_target_study")
def _(s, d):
    """Twenty trials for each target, failure probability and proxy: means of recall, precision and oracle calls."""
    rows = []
    settings = [(target, delta, "exact") for delta in (0.2, 0.4) for target in (0.7, 0.8, 0.9)]
    for proxy, expr in PROXIES.items():
        for (target, delta, _bound), trials in JunkTrials(s, d, expr, 20).judged(settings).items():
            r, p, c = (float(np.mean([t[i] for t in trials])) for i in range(3))
            rows.append((proxy, delta, target, round(r, 6), round(p, 6), round(c, 2)))
    return table(s, rows, "proxy string, delta double, target double, recall double, precision double, oracle_calls double")


@query("w5_failure_study")
def _(s, d):
    """Fifty trials for each failure probability and bound at targets of 0.9: the share of trials that miss one."""
    rows = []
    settings = [(0.9, delta, bound) for bound in ("exact", "normal") for delta in (0.05, 0.1, 0.2, 0.4)]
    for proxy in ("weak", "useless"):
        for (_t, delta, bound), trials in JunkTrials(s, d, PROXIES[proxy], 50).judged(settings).items():
            failed = float(np.mean([r < 0.9 or p < 0.9 for r, p, _ in trials]))
            rows.append((proxy, bound, delta, round(failed, 6), failed <= delta))
    return table(s, rows, "proxy string, bound string, delta double, failure_share double, within boolean")


# --- W6, W7: programs ----------------------------------------------------------------------
@query("w6_join_project_reduce", f"SELECT string_agg(DISTINCT t, ' ' ORDER BY t) AS reduced FROM (SELECT lower(regexp_extract(text, '([A-Za-z]+)', 1)) AS t FROM documents WHERE doc_id IN (SELECT doc_id FROM ({oc.PAIRS_SQL}))) WHERE t <> ''")
def _(s, d):
    joined = oc._contains(s, d, "semi").df
    digests = nl_project(joined, "a digest of {text}", "digest", RuleModel(project=oc.FIRST_WORD))
    return nl_reduce(digests, "all of {digest}", oc.TERMS, key="doc_id", text="digest").df.select("reduced")


@query("w7_similarity_self_join", f"SELECT lk AS item_id, rk AS other_id, (row_number() OVER (PARTITION BY lk ORDER BY sim DESC, rk))::INTEGER AS rank FROM ({oc.sims_sql('benchmark', 'item_id', 'text', 'benchmark', 'item_id', 'text')}) QUALIFY rank <= 10")
def _(s, d):
    items = read_table(s, d, "benchmark")
    out = nl_similar_join(items, items, "text", "text", 10, left_key="item_id", right_key="item_id", embedder=oc.UNIGRAMS)
    return out.select(F.col("left_key").alias("item_id"), F.col("right_key").alias("other_id"), "rank")


@query("w7_contradicting_pairs", "SELECT a.item_id AS a, b.item_id AS b FROM benchmark a JOIN benchmark b ON a.item_id < b.item_id AND length(a.text) = length(b.text)")
def _(s, d):
    """A self join with a pair rule: here items of equal length stand for pairs that contradict each other."""
    items = read_table(s, d, "benchmark")
    rule = RuleModel(predicate="left_item_id < right_item_id AND length(left_text) = length(right_text)")
    out = nl_join(items, items, "{text:left} ({item_id:left}) contradicts {text:right} ({item_id:right})", rule, left_key="item_id", right_key="item_id")
    return out.df.select(F.col("item_id").alias("a"), F.col("right_item_id").alias("b"))


@query("w7_near_copies", f"SELECT lk AS item_id, rk AS doc_id FROM ({oc.sims_sql('benchmark', 'item_id', 'text', 'documents', 'doc_id', 'text')}) WHERE sim >= 0.5")
def _(s, d):
    left, right = oc.UNIGRAMS.embed(read_table(s, d, "benchmark"), "text", "v"), oc.UNIGRAMS.embed(oc.docs(s, d, "doc_id", "text"), "text", "v")
    return similar_pairs(left, right, "item_id", "v", "doc_id", "v", least=0.5).select(F.col("lk").alias("item_id"), F.col("rk").alias("doc_id"))


# --- streams -------------------------------------------------------------------------------
def _stream(s, d, make) -> DataFrame:
    base = f"{shared_folder(s)}/nlops-stream-{uuid.uuid4().hex[:10]}"
    return streams.run_to_parquet(make(streams.read_events(s, streams.land(read_table(s, d, "events")))), f"{base}/out", f"{base}/state")


CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"


@query("stream_tumbling_counts", f"SELECT strftime(a, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 6) AS total FROM (SELECT date_trunc('hour', ts) AS a, event_type, value FROM events) WHERE a + INTERVAL 1 HOUR <= {CLOSED} GROUP BY ALL")
def _(s, d):
    out = _stream(s, d, lambda e: streams.window_counts(e, "tumbling", by=["event_type"]))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", "total")


@query("stream_sliding", f"SELECT strftime(a, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 6) AS total FROM (SELECT time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE AS a, value FROM events, range(0, 4) t(i)) WHERE a + INTERVAL 1 HOUR <= {CLOSED} GROUP BY a")
def _(s, d):
    out = _stream(s, d, lambda e: streams.window_counts(e, "sliding", slide="15 minutes"))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "total")


@query("stream_session", f"""WITH m AS (SELECT user_id, ts, value, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM m)
SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, user_id, count(*) AS n, round(sum(value), 6) AS total FROM g GROUP BY user_id, no HAVING max(ts) + INTERVAL 30 MINUTE <= {CLOSED}""")
def _(s, d):
    out = _stream(s, d, lambda e: streams.window_counts(e, "session", by=["user_id"]))
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "user_id", "n", "total")


@query("stream_frozen_filter", "SELECT event_id FROM events WHERE value >= 0.8 * 100 OR (value >= 20 AND event_type = 'purchase')")
def _(s, d):
    proxy = RuleModel(score="least(1.0D, value / 100.0D)")
    oracle = RuleModel(predicate="event_type = 'purchase'")
    return _stream(s, d, lambda e: streams.frozen_filter(e.select("event_id", "value", "event_type"), "{value} of {event_type} matters", proxy, oracle, 0.2, 0.8)).select("event_id")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def _(s, d):
    """First of each user and type within the watermark; the 30 days here are one watermark span."""
    return _stream(s, d, lambda e: streams.first_of_each(e.select("ts", "user_id", "event_type"), ["user_id", "event_type"], late="40 days")).select("user_id", "event_type")


@query("stream_running_top", "SELECT user_id, (list(value ORDER BY value DESC)[1:3])[1] AS best FROM events GROUP BY user_id")
def _(s, d):
    base = f"{shared_folder(s)}/nlops-stream-{uuid.uuid4().hex[:10]}"
    before = s.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    name = f"top_{uuid.uuid4().hex[:8]}"
    try:
        out = streams.run_to_table(streams.running_top(streams.read_events(s, streams.land(read_table(s, d, "events")))), name, f"{base}/state", "update")
    finally:
        if before is None:
            s.conf.unset("spark.sql.streaming.stateStore.providerClass")
        else:
            s.conf.set("spark.sql.streaming.stateStore.providerClass", before)
    return out.groupBy("user_id").agg(F.max(F.col("best")[0]).alias("best"))
