import hashlib
import random

import numpy as np

from spark_nlops.baselines import rewriter
from spark_nlops.baselines.budget_filter import budget_join
from spark_nlops.models.rules import RuleModel
from spark_nlops.operators.join import nl_join
from spark_nlops.operators.search import embedded
from spark_nlops.result import SampleSpec
from spark_nlops.stats.hashing import md5_heads
from spark_nlops.vectors.embed import Embedder, HashedNgrams
from spark_nlops.workloads import common as w


class Watched(Embedder):
    """Keeps the columns that were embedded, as frames."""

    def __init__(self, n, dim):
        self.base, self.given = HashedNgrams(n, dim), []

    def embed(self, df, text, out="vec"):
        self.given.append(df.select(text))
        return self.base.embed(df, text, out)


def sides(spark):
    rng = random.Random(5)
    items = [" ".join(f"w{rng.randrange(3000)}" for _ in range(12)) for _ in range(12)]
    texts = [" ".join(f"w{rng.randrange(3000)}" for _ in range(30)) + " " + items[i % 12] for i in range(60)]
    return spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")


def test_hashes_of_many_texts_are_those_of_each():
    rng = random.Random(2)
    texts = [bytes(rng.randrange(256) for _ in range(rng.choice([0, 1, 3, 4, 20, 54, 55, 56, 57, 64, 150]))) for _ in range(9000)]
    assert md5_heads(texts).tolist() == [int(hashlib.md5(t).hexdigest()[:8], 16) for t in texts]
    assert len(md5_heads([])) == 0


def test_vectors_of_many_texts():
    texts = ["a b c d a b c", "", None, "one two", "É  ü\n" * 40 + "z" * 80]
    for n, dim in ((1, 16), (3, 64)):
        for text, v in zip(texts, HashedNgrams(n, dim).many(texts)):
            words = (text or "").lower().split()
            want = np.zeros(dim)
            for i in range(len(words) - n + 1):
                want[int(hashlib.md5(" ".join(words[i : i + n]).encode()).hexdigest()[:8], 16) % dim] += 1
            assert (v == (want / np.sqrt((want**2).sum()) if want.any() else want)).all()


def test_stored_vectors_serve_blocking(spark):
    left, right = sides(spark)
    plain, watched = HashedNgrams(1, 64), Watched(1, 64)
    args = (left, right, w.CONTAINS, w.contains_oracle())
    runs = [rewriter.blocking_join(*args, left_key="doc_id", right_key="item_id", embedder=e, budget=180, seed=seed, vectors=v) for e, v in ((plain, None), (watched, embedded(left, "text", "doc_id", plain))) for seed in (1,)]
    assert runs[0].plan["success"] and {tuple(r) for r in runs[0].df.collect()} == {tuple(r) for r in runs[1].df.collect()} and runs[0].calls == runs[1].calls
    assert [f.count() for f in watched.given] == [12]  # the right side's alone


def test_a_guess_that_is_the_text_is_embedded_once(spark):
    left, right = sides(spark)
    watched = Watched(1, 64)
    got = nl_join(left, right, w.CONTAINS, w.contains_oracle(), left_key="doc_id", right_key="item_id", plan="auto", embedder=watched, projector=RuleModel(project="text"), recall=0.9, precision=0.9, sample=SampleSpec(min_rows=300, seed=1))
    assert {(r.doc_id, r.right_item_id) for r in got.df.collect()} == {(i, i % 12) for i in range(60)}
    assert sum(1 for f in watched.given for r in f.collect() if len(r[0].split()) == 42) == 60


def test_budget_join_shows_texts_of_its_batches_only(spark):
    left, right = sides(spark)
    shown = []

    class Kept(RuleModel):
        def label(self, df, template, out="label"):
            shown.append(df.count())
            return super().label(df, template, out)

    got = budget_join(left, right, w.CONTAINS, Kept(predicate="contains(left_text, right_text)"), left_key="doc_id", right_key="item_id", embedder=HashedNgrams(1, 64), budget=90, candidates=6, batch=30)
    assert got.calls["oracle"] == sum(shown) and max(shown) <= 30 and got.calls["embedding"] == 360
    assert "left_text" not in got.df._jdf.queryExecution().analyzed().toString()
