import random

from pyspark.sql import functions as F

from spark_nlops.models.rules import RuleModel
from spark_nlops.operators.join import nl_join
from spark_nlops.vectors import containment
from spark_nlops.workloads import common as w


class Counting(RuleModel):
    """Keeps the frames it was shown."""

    def label(self, df, template, out="label"):
        self.shown = df
        return super().label(df, template, out)


def near_copies(n):
    """Texts of 600 words that differ in one word each, at different places."""
    rng = random.Random(7)
    words = [f"{rng.random():.9f}" for _ in range(600)]
    return [" ".join([*words[: 5 * i], f"changed{i}", *words[5 * i + 1 :]]) for i in range(n)]


def test_near_copies_are_no_candidates_of_each_other(spark):
    texts = near_copies(60)
    left = spark.createDataFrame([(i, f"head {t} tail") for i, t in enumerate(texts)], "doc_id long, text string")
    right = spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")
    met = containment.containment_candidates(left, right, "doc_id", "text", "item_id", "text")
    assert {(r.lk, r.rk) for r in met.collect()} == {(i, i) for i in range(60)}  # 8 choices left many of the 3 600


def test_copies_of_a_part_are_shown_once(spark):
    texts = near_copies(6)
    left = spark.createDataFrame([(i, f"head {t} tail") for i, t in enumerate(texts)], "doc_id long, text string")
    right = spark.createDataFrame([(i, texts[i % 6]) for i in range(60)], "item_id long, text string")
    rule = Counting(predicate="contains(left_text, right_text)", holds=("left_text", "right_text"))
    out = nl_join(left, right, w.CONTAINS, rule, left_key="doc_id", right_key="item_id")
    assert {(r.doc_id, r.right_item_id) for r in out.df.collect()} == {(i % 6, i) for i in range(60)} and out.calls == {"oracle": 360}
    assert rule.shown.count() == 6


def test_parts_of_texts_that_repeat_themselves_are_found(spark):
    texts = ["ab" * 5000, "ab" * 3000 + "c", "x" * 400]
    parts = ["ab" * 100, "ba" * 60, "b" + "ab" * 40 + "c", "x" * 61, "x" * 401, "ab" * 5000, "ab" * 5001]
    left = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    right = spark.createDataFrame(list(enumerate(parts)), "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in w.contained_pairs(left, right).select(F.col("doc_id"), "item_id").collect()}
    assert got == {(i, j) for i, t in enumerate(texts) for j, p in enumerate(parts) if p in t}
