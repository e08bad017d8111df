"""Cost and accuracy measures over DataFrames."""

from __future__ import annotations

import ast
import inspect
import textwrap
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.text import token_estimate
from .result import SampleSpec

#: Seconds per oracle call in the reference's own estimate (total seconds by total calls); for modelled times only.
MODELLED_SECONDS_PER_CALL = 2_144_560 / 6_092_500


def accuracy(pred: DataFrame, truth: DataFrame, key: str, pred_col: str, truth_col: str) -> DataFrame:
    """Share of truth rows whose prediction is equal (a missing prediction is wrong)."""
    joined = truth.select(key, F.col(truth_col).alias("_t")).join(pred.select(key, F.col(pred_col).alias("_p")), key, "left")
    return joined.agg(F.avg(F.coalesce((F.col("_t") == F.col("_p")).cast("double"), F.lit(0.0))).alias("accuracy"), F.count("*").alias("n_rows"))


def set_precision_recall(out: DataFrame, gold: DataFrame, keys: list[str]) -> DataFrame:
    """Precision (1 if nothing came out) and recall (1 if nothing was due) of a set of keys."""
    tagged = out.select(*keys).distinct().withColumn("_o", F.lit(1)).unionByName(gold.select(*keys).distinct().withColumn("_g", F.lit(1)), allowMissingColumns=True)
    both = tagged.groupBy(*keys).agg(F.max("_o").alias("o"), F.max("_g").alias("g"))
    hits, n_out, n_gold = F.count(F.when((F.col("o") == 1) & (F.col("g") == 1), 1)), F.count("o"), F.count("g")
    return both.agg(
        F.when(n_out > 0, hits / n_out).otherwise(F.lit(1.0)).alias("precision"), F.when(n_gold > 0, hits / n_gold).otherwise(F.lit(1.0)).alias("recall"), n_out.alias("n_out"), n_gold.alias("n_gold")
    )


def relative_accuracy(optimized: float, reference: float) -> float:
    return optimized / reference if reference else 1.0


def rank_precision(ranked: DataFrame, truth: DataFrame, query: str, item: str, k: int) -> DataFrame:
    """Mean over queries with relevant items of hits in the first k by min(k, number of relevant items)."""
    due = truth.select(query, item).distinct()
    sizes = due.groupBy(query).agg(F.count("*").alias("due"))
    hits = ranked.filter(F.col("rank") <= k).join(due, [query, item], "left_semi").groupBy(query).agg(F.count("*").alias("hits"))
    share = F.coalesce("hits", F.lit(0)) / F.least(F.lit(k), F.col("due"))
    return sizes.join(hits, query, "left").agg(F.avg(share).alias("rank_precision"), F.count("*").alias("n_queries"))


def ndcg(ranked: DataFrame, gains: DataFrame, query: str, item: str, gain: str, k: int) -> DataFrame:
    """Mean over queries with a positive ideal of gain / log2(rank + 1) against the ideal order."""
    got = ranked.filter(F.col("rank") <= k).join(gains, [query, item]).groupBy(query).agg(F.sum(F.col(gain) / F.log2(F.col("rank") + 1)).alias("dcg"))
    ideal = gains.withColumn("_r", F.row_number().over(Window.partitionBy(query).orderBy(F.desc(gain), item))).filter(F.col("_r") <= k)
    best = ideal.groupBy(query).agg(F.sum(F.col(gain) / F.log2(F.col("_r") + 1)).alias("idcg")).filter("idcg > 0")
    return best.join(got, query, "left").agg(F.avg(F.coalesce("dcg", F.lit(0.0)) / F.col("idcg")).alias("ndcg"), F.count("*").alias("n_queries"))


def prompt_tokens(df: DataFrame, prompt, by: str) -> DataFrame:
    """Calls and estimated prompt tokens by route."""
    return df.groupBy(by).agg(F.count("*").alias("calls"), F.sum(token_estimate(prompt)).alias("tokens"))


def timed(action: Callable[[], object], runs: int = 1) -> tuple[object, float]:
    """The last result and the mean wall time."""
    total, out = 0.0, None
    for _ in range(runs):
        start = time.perf_counter()
        out = action()
        total += time.perf_counter() - start
    return out, total / runs


def extrapolate(calls: int, seconds_per_call: float = MODELLED_SECONDS_PER_CALL) -> float:
    """Estimated time of calls that were not made, by linear scaling; always labelled as modelled."""
    return calls * seconds_per_call


def trial_study(spark: SparkSession, trial: Callable[[SampleSpec], tuple[float, float, int]], trials: int, recall: float, precision: float, **spec) -> DataFrame:
    """Recall, precision, oracle calls and joint failure of seeded trials."""
    rows = []
    for seed in range(trials):
        r, p, calls = trial(SampleSpec(seed=seed, **spec))
        rows.append((seed, float(r), float(p), int(calls), bool(r < recall - 1e-12 or p < precision - 1e-12)))
    return spark.createDataFrame(rows, "seed int, recall double, precision double, oracle_calls long, failed boolean")


def lines_of_code(function: Callable) -> int:
    """Lines of a function's source that hold code: no blank lines, comments or docstring."""
    source = textwrap.dedent(inspect.getsource(function))
    body = ast.parse(source).body[0].body
    first = body[0]
    said = range(first.lineno, first.end_lineno + 1) if isinstance(first, ast.Expr) and isinstance(getattr(first, "value", None), ast.Constant) else range(0)
    return sum(1 for n, line in enumerate(source.splitlines(), 1) if line.strip() and not line.strip().startswith("#") and n not in said)


def success_rate(runs: DataFrame) -> DataFrame:
    return runs.agg(F.avg(F.col("success").cast("double")).alias("success_rate"), F.count("*").alias("n_runs"))
