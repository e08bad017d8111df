import random

from spark_nlops.models.rules import RuleModel
from spark_nlops.operators.join import nl_join
from spark_nlops.vectors import containment
from spark_nlops.workloads import common as w


def made(rng):
    alphabet = "abcé ü🙂\n"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.choice([0, 1, 3, 30, 90, 400]))) for _ in range(60)] + [None, "x" * 300]
    parts = ["", "x", "xxxx", "x" * 60, "x" * 61, "x" * 301, None, "🙂" * 100]
    for n in (1, 2, 4, 5, 15, 16, 17, 40, 59, 60, 61, 90, 200):
        for _ in range(6):
            t = rng.choice([t for t in texts if t and len(t) >= 20])
            at = rng.randrange(max(1, len(t) - n))
            parts.append(t[at : at + n])
    return texts, parts + parts[-5:]


def test_candidates_hold_every_contained_pair(spark):
    texts, parts = made(random.Random(3))
    left = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    right = spark.createDataFrame([(i, t) for i, t in enumerate(parts)], "item_id long, text string")
    want = {(i, j) for i, t in enumerate(texts) for j, p in enumerate(parts) if t is not None and p is not None and p in t}
    met = [(r.lk, r.rk) for r in containment.containment_candidates(left, right, "doc_id", "text", "item_id", "text").collect()]
    assert set(met) >= want and len(met) == len(set(met))
    got = [(r.doc_id, r.item_id) for r in w.contained_pairs(left, right).collect()]
    assert set(got) == want and len(got) == len(want)
    out = nl_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id")
    assert {(r.doc_id, r.right_item_id) for r in out.df.collect()} == want and out.calls == {"oracle": len(texts) * len(parts)}


def test_rules_of_containment_ask_about_few_pairs(spark):
    rng = random.Random(4)
    words = [f"{rng.random():.12f}" for _ in range(3000)]
    left = spark.createDataFrame([(i, " ".join(words[10 * i : 10 * i + 30])) for i in range(200)], "doc_id long, text string")
    right = spark.createDataFrame([(i, " ".join(words[10 * i : 10 * i + 10])) for i in range(200)], "item_id long, text string")
    met = containment.containment_candidates(left, right, "doc_id", "text", "item_id", "text").count()
    assert 597 <= met < 700  # of 40 000
    out = nl_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id")
    assert "NestedLoop" not in out.df._jdf.queryExecution().executedPlan().toString() and "CartesianProduct" not in out.df._jdf.queryExecution().executedPlan().toString()
    assert out.df.count() == 597
    assert RuleModel(predicate="true").holds is None
