"""A filter under a call budget by active learning on vectors; no guarantee.

A seeded first batch is labelled and a logistic model fitted; each further batch is
half most likely positives and half most uncertain rows; when the budget is spent,
the result is the labelled positives and the rows predicted positive.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..models.base import ModelBackend
from ..result import NLResult
from ..staging import staged
from ..stats.hashing import uniform
from ..template import Template


def first_batch(df: DataFrame, key: str, size: int, seed: int) -> DataFrame:
    return df.orderBy(uniform(F.col(key), seed), key).limit(size)


def _fit(x: np.ndarray, y: np.ndarray, rounds: int = 300, rate: float = 1.0, penalty: float = 1e-3) -> np.ndarray:
    w = np.zeros(x.shape[1] + 1)
    x = np.hstack((x, np.ones((len(x), 1))))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w -= rate * (x.T @ (p - y) / len(y) + penalty * w)
    return w


def _probability(vec: str, w: np.ndarray) -> Column:
    z = F.aggregate(F.zip_with(vec, F.array(*[F.lit(float(v)) for v in w[:-1]]), lambda a, b: a * b), F.lit(float(w[-1])), lambda s, t: s + t)
    return 1 / (1 + F.exp(-z))


def _keys(rows: DataFrame, key: str, found: list) -> DataFrame:
    """At most as many keys as the budget, as a table."""
    return rows.sparkSession.createDataFrame([(x,) for x in found], T.StructType([T.StructField(key, rows.schema[key].dataType)]))


def budget_filter(df: DataFrame, template: str | Template, oracle: ModelBackend, *, key: str, vec: str, budget: int, batch: int = 50, seed: int = 0, shown: Callable[[DataFrame], DataFrame] | None = None) -> NLResult:
    """df has a vector column; at most ``budget`` rows, collected batch by batch, are ever on the driver.

    ``shown`` gives the rows of a batch the columns that the oracle is shown, where df hasn't got them.
    """
    template = Template(template) if isinstance(template, str) else template
    rows = staged(df, "budget")
    known: dict = {}
    xs, ys = [], []
    todo = first_batch(rows, key, min(batch, budget), seed)
    w = None
    while True:
        if shown is not None:  # a batch is drawn once, then looked up
            todo = shown(F.broadcast(rows.sparkSession.createDataFrame(todo.collect(), todo.schema)))
        told = oracle.label(todo, template, "_label").select(key, vec, "_label").collect()
        for r in told:
            known[r[key]] = bool(r["_label"])
            xs.append(list(r[vec]))
            ys.append(float(bool(r["_label"])))
        if len(set(ys)) == 2:
            w = _fit(np.array(xs), np.array(ys))
        left = budget - len(known)
        if left <= 0 or not told:
            break
        open_rows = rows.join(F.broadcast(_keys(rows, key, list(known))), key, "left_anti")
        if open_rows.limit(1).count() == 0:
            break
        size = min(batch, left)
        if w is None:
            todo = open_rows.orderBy(uniform(F.col(key), seed), key).limit(size)
        else:
            p = F.round(_probability(vec, w), 12)
            likely = open_rows.orderBy(F.desc(p), key).limit(size - size // 2)
            unsure = open_rows.orderBy(F.abs(p - 0.5), key).limit(size // 2)
            todo = likely.unionByName(unsure).dropDuplicates([key])
    positive = [k for k, v in known.items() if v]
    predicted = F.lit(False) if w is None else (_probability(vec, w) >= 0.5)
    told = rows.join(F.broadcast(_keys(rows, key, positive)), key, "left_semi")
    guessed = rows.join(F.broadcast(_keys(rows, key, list(known))), key, "left_anti").filter(predicted)
    out = told.unionByName(guessed) if known else rows.limit(0)
    return NLResult(out.select(*df.columns), {"oracle": len(known), "embedding": rows.count()}, {"plan": "budget"})


def budget_join(left: DataFrame, right: DataFrame, template: str, oracle: ModelBackend, *, left_key: str, right_key: str, embedder, budget: int, candidates: int = 20, batch: int = 50, seed: int = 0) -> NLResult:
    """The same learner on pairs: each left row's most similar candidates, described by the product of both vectors."""
    from ..operators.join import pair_rows
    from ..vectors.similarity import similar_pairs

    t = Template(template)
    l = staged(embedder.embed(left.select(left_key, F.coalesce(t.columns("left")[0], F.lit("")).alias("_t")), "_t", "lv").drop("_t"), "left")
    r = staged(embedder.embed(right.select(right_key, F.coalesce(t.columns("right")[0], F.lit("")).alias("_t")), "_t", "rv").drop("_t"), "right")
    near = similar_pairs(l, r, left_key, "lv", right_key, "rv", k=candidates).select("lk", "rk")
    described = near.join(l.withColumnRenamed(left_key, "lk"), "lk").join(r.withColumnRenamed(right_key, "rk"), "rk")
    described = described.withColumn("vec", F.zip_with("lv", "rv", lambda a, b: a * b)).withColumn("pair", F.concat_ws("-", "lk", "rk")).drop("lv", "rv")
    # texts join a batch, not all candidates
    shown = lambda todo: pair_rows(left, right, t, left_key, right_key, todo)
    out = budget_filter(described, t, oracle, key="pair", vec="vec", budget=budget, batch=batch, seed=seed, shown=shown)
    return NLResult(out.df.select("lk", "rk"), out.calls, {"plan": "budget join"})
