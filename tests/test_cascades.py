"""Cuts, bounds, sampling and routing: hand-worked cases and repeated trials."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from spark_nlops.models.rules import LookupModel, NoisyModel, RuleModel
from spark_nlops.operators.filter import nl_filter, route
from spark_nlops.result import GuaranteeSpec, SampleSpec
from spark_nlops.stats import bounds, calibrate, cuts, sampling
from spark_nlops.stats.hashing import uniform
from spark_nlops.template import Template
from spark_nlops.workloads import common as w
from spark_nlops.workloads.studies import PROXIES, JunkTrials


def sample(scores, labels):
    return cuts.Sample(np.array(scores, float), np.array(labels, float), np.ones(len(scores)))


def test_bounds_against_known_values():
    assert bounds.z_value(0.05) == pytest.approx(1.6448536, abs=1e-6)
    # a lower bound for n of n successes is delta^(1/n)
    assert bounds.proportion_lower(22, 22, 0.1) == pytest.approx(0.1 ** (1 / 22), abs=1e-9)
    assert bounds.beta_cdf(0.3, 2, 5) == pytest.approx(0.579825, abs=1e-6)
    assert bounds.proportion_upper(0, 10, 0.05) == pytest.approx(1 - 0.05**0.1, abs=1e-9)
    assert bounds.effective_size(np.array([1.0, 1, 1, 1])) == 4 and bounds.effective_size(np.zeros(0)) == 0
    low, high = bounds.mean_bounds(np.array([0.0, 1.0] * 50), 0.05)
    assert low == pytest.approx(0.5 - 1.6448536 * 0.05) and high == pytest.approx(0.5 + 1.6448536 * 0.05)


@pytest.mark.parametrize("positives, certified", [(0, False), (1, False), (21, False), (22, True)])
def test_recall_needs_enough_positives(positives, certified):
    assert cuts.positives_needed(0.9, 0.1) == 22
    s = sample(np.linspace(0.1, 1, 60), [0] * (60 - positives) + [1] * positives)
    assert (cuts.recall_cut(s, 0.9, 0.1) > cuts.ALWAYS) == certified


def test_degenerate_samples():
    assert cuts.precision_cut(sample([], []), 0.9, 0.2) == cuts.NEVER
    assert cuts.precision_cut(sample([0.5] * 50, [0] * 50), 0.9, 0.2) == cuts.NEVER
    everything = sample(np.linspace(0, 1, 400), [1] * 400)
    lo, hi = cuts.two_cuts(everything, 0.9, 0.9, 0.2)
    assert hi >= lo and hi < 1
    assert cuts.two_cuts(everything, 0.9, None, 0.2)[1] == cuts.NEVER
    assert cuts.two_cuts(everything, None, 0.9, 0.2)[0] == cuts.ALWAYS


def test_route_boundaries(spark):
    df = spark.createDataFrame([(i / 10,) for i in range(11)], "s double")
    got = {round(r.s, 1): r.r for r in df.withColumn("r", route(F.col("s"), 0.3, 0.7)).collect()}
    assert got[0.3] == "ask" and got[0.7] == "accept" and got[0.2] == "reject" and got[0.6] == "ask"
    assert {r.r for r in df.withColumn("r", route(F.col("s"), 0.5, 0.5)).collect()} == {"accept", "reject"}
    assert {r.r for r in df.withColumn("r", route(F.col("s"), cuts.ALWAYS, cuts.NEVER)).collect()} == {"ask"}


@pytest.mark.parametrize("proxy", list(PROXIES))
@pytest.mark.parametrize("delta", [0.2, 0.4])
def test_failure_share_stays_below_delta(spark, sf01, proxy, delta):
    setting = (0.9, delta, "exact")
    trials = JunkTrials(spark, sf01, PROXIES[proxy], 100).judged([setting])[setting]
    assert len(trials) == 100
    failed = np.mean([r < 0.9 or p < 0.9 for r, p, _ in trials])
    assert failed <= delta + 2 * math.sqrt(delta * (1 - delta) / 100)


def test_weaker_proxies_and_higher_targets_cost_more(spark, sf01):
    mean = {}
    for proxy in ("strong", "useless"):
        settings = [(target, 0.2, "exact") for target in (0.6, 0.9)]
        for (target, _, _), trials in JunkTrials(spark, sf01, PROXIES[proxy], 20).judged(settings).items():
            mean[proxy, target] = np.mean([calls for _, _, calls in trials])
    assert mean["useless", 0.9] > mean["strong", 0.9] and mean["useless", 0.9] > mean["useless", 0.6] and mean["strong", 0.9] >= mean["strong", 0.6]


def test_calibration_exact_and_sketch(spark):
    df = spark.createDataFrame([(i, float(i % 7)) for i in range(700)] + [(999, None)], "k long, s double")
    exact = {r.k: r.scaled for r in calibrate.quantile_scale(df, "s").collect()}
    assert exact[999] is None and exact[6] == 1.0 and exact[0] == pytest.approx(1 / 7)
    near = {r.k: r.scaled for r in calibrate.quantile_scale(df, "s", mode="sketch").collect()}
    assert all(abs(near[k] - exact[k]) < 0.03 for k in exact if k != 999)
    assert calibrate.quantile_scale(df.limit(0), "s").count() == 0


def test_samples_do_not_depend_on_partitions(spark, sf01):
    df = spark.read.parquet(f"{sf01}/documents.parquet").select("doc_id", (F.col("n_chars") / 40_000).alias("s"))
    draws = [sorted(r.doc_id for r in sampling.weighted_sample(df.repartition(p), "s", "doc_id", SampleSpec(min_rows=100))[0].collect()) for p in (1, 8, 31)]
    assert draws[0] == draws[1] == draws[2] and 60 < len(draws[0]) < 140
    counts = sampling.draw_with_replacement(df, "s", "doc_id", SampleSpec(min_rows=300)).agg(F.sum("draws")).first()[0]
    assert 220 < counts < 380
    assert 0.45 < df.agg(F.avg(uniform(F.col("doc_id"), 1))).first()[0] < 0.55


def test_filter_plans(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    gold = {r.doc_id for r in nl_filter(docs, w.JUNK, w.junk_oracle(), plan="reference").df.collect()}
    for targets in ({"recall": 0.9}, {"precision": 0.9}, {"recall": 0.9, "precision": 0.9}):
        got = nl_filter(docs, w.JUNK, w.junk_oracle(), proxy=w.junk_proxy(), key="doc_id", sample=SampleSpec(min_rows=300), **targets)
        out = {r.doc_id for r in got.df.collect()}
        if "recall" in targets:
            assert len(out & gold) >= 0.9 * len(gold)
        if "precision" in targets:
            assert len(out & gold) >= 0.9 * len(out)
        assert sum(got.calls[k] for k in ("accept", "reject", "oracle_band")) == docs.count()
        assert got.df.columns == docs.columns
    one = docs.limit(1)
    assert nl_filter(one, w.JUNK, w.junk_oracle(), proxy=w.junk_proxy(), key="doc_id", recall=0.9).df.count() <= 1
    assert nl_filter(docs.limit(0), w.JUNK, w.junk_oracle(), proxy=w.junk_proxy(), key="doc_id", recall=0.9, precision=0.9).df.count() == 0
    nulls = spark.createDataFrame([(1, None), (2, "ABC###")], "doc_id long, text string")
    assert [r.doc_id for r in nl_filter(nulls, w.JUNK, w.junk_oracle(), plan="reference").df.collect()] == [2]


def test_certifiability_is_explained(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    rare = RuleModel(predicate="doc_id = 5")
    got = nl_filter(docs, "{text} {doc_id} is number five", rare, proxy=RuleModel(score="1.0D / (1 + doc_id)"), key="doc_id", recall=0.9, precision=0.9)
    assert [r.doc_id for r in got.df.collect()] == [5] and "positives" in got.plan["why"]


def test_models(spark):
    df = spark.createDataFrame([(i, f"t{i}") for i in range(200)], "k long, t string")
    truth = LookupModel(spark.createDataFrame([(i, i % 2) for i in range(100)], "k long, y int"), "k", "y")
    got = truth.label(df, Template("{t}")).collect()
    assert sum(bool(r.label) for r in got) == 50 and sum(r.label is None for r in got) == 100
    noisy = NoisyModel(RuleModel(predicate="k >= 100"), 0.2, 3, "k")
    wrong = noisy.label(df, Template("{t}")).filter("label <> (k >= 100)").count()
    assert 20 <= wrong <= 60
    with pytest.raises(NotImplementedError):
        RuleModel().label(df, Template("{t}"))
    with pytest.raises(ValueError):
        GuaranteeSpec(recall=1.5)


def test_draws_of_a_heavy_row_are_not_capped(spark):
    df = spark.createDataFrame([(1, 1.0)] + [(i, 0.0) for i in range(2, 500)], "doc_id long, s double")
    got = {r.doc_id: r for r in sampling.draw_with_replacement(df, "s", "doc_id", SampleSpec(min_rows=300)).collect()}
    assert got[1].rate > 100 and abs(got[1].draws - got[1].rate) < 6 * got[1].rate ** 0.5


def test_quantiles_of_hot_scores(spark):
    scores = [0.0] * 400 + [0.25] * 9 + [i / 1000 for i in range(300)] + [None] * 3
    df = spark.createDataFrame(list(enumerate(scores)), "id long, s double").repartition(5)
    got = {r.id: r.q for r in calibrate.quantile_scale(df, "s", "q").collect()}
    known = [s for s in scores if s is not None]
    assert len(got) == len(scores)
    for i, s in enumerate(scores):
        assert got[i] is None if s is None else abs(got[i] - sum(x <= s for x in known) / len(known)) < 1e-12
