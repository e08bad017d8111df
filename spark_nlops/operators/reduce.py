"""NL aggregate: hierarchical reduction, sequential fold, partitioners and packing by a token budget."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import token_estimate
from ..models.base import ModelBackend
from ..result import NLResult
from ..staging import staged
from ..template import Template

#: Partial texts of a group that are numbered in one task; more go on within their buckets, then in ranges of neighbours.
TOGETHER = 100_000
Partitioner = Callable[[DataFrame], tuple[Column, Column]]


def pack(df: DataFrame, groups: list[str], bucket: str, order: str, tokens: str, budget: int, fanin: int) -> DataFrame:
    """Adds ``bin``: rows of a bucket in order, filled up to a token budget and at most ``fanin`` rows.

    Bins are cut where the running token count passes a multiple of the budget, so no
    bin holds more than the budget plus one row; ``fanin`` cuts them further.
    """
    running = Window.partitionBy(*groups, bucket).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    cut = F.floor((F.sum(tokens).over(running) - F.col(tokens)) / F.lit(budget))
    placed = df.withColumn("_cut", cut)
    place = F.row_number().over(Window.partitionBy(*groups, bucket, "_cut").orderBy(order)) - 1
    return placed.withColumn("bin", F.struct(F.col(bucket).alias("bucket"), F.col("_cut").alias("cut"), F.floor(place / F.lit(fanin)).alias("piece"))).drop("_cut")


def fit(df: DataFrame, text: str, budget: int, overflow: str) -> DataFrame:
    """Rows longer than the budget are split into several, truncated, or refused."""
    words = F.filter(F.split(F.col(text), r"\s+"), lambda w: w != "")
    if overflow == "split":
        pieces = F.expr(f"CASE WHEN size(_w) <= {budget} THEN array(`{text}`) ELSE transform(sequence(0, (size(_w) - 1) div {budget}), i -> array_join(slice(_w, i * {budget} + 1, {budget}), ' ')) END")
        return df.withColumn("_w", words).select(*[c for c in df.columns if c != text], F.posexplode(pieces).alias("_piece", text))
    if overflow == "truncate":
        return df.withColumn(text, F.when(F.size(words) <= budget, F.col(text)).otherwise(F.array_join(F.slice(words, 1, budget), " "))).withColumn("_piece", F.lit(0))
    if overflow == "error":
        return df.withColumn(text, F.when(F.size(words) <= budget, F.col(text)).otherwise(F.raise_error(F.lit("a row is longer than the token budget")))).withColumn("_piece", F.lit(0))
    raise ValueError("overflow is split, truncate or error")


def nl_reduce(
    df: DataFrame,
    template: str | Template,
    reducer: ModelBackend,
    *,
    key: str,
    text: str,
    by: list[str] | None = None,
    pattern: str = "tree",
    fanin: int = 8,
    token_budget: int = 2048,
    overflow: str = "split",
    partitioner: Partitioner | None = None,
    buckets: int | None = None,
    provenance: bool = False,
) -> NLResult:
    """One text for each group (all rows are one group without ``by``).

    ``tree``: packs of rows become partial texts, packs of these become fewer, until
    one is left; each level is one shuffle.  ``fold``: rows in key order, each call
    takes the text so far and the next row.  A partitioner gives a bucket and an order
    column, for reducers to which the order inside a prompt matters.  ``n_sources``
    counts the rows behind each text; ``provenance`` also lists their keys, which is
    meant for groups whose keys fit one row.
    """
    template = Template(template) if isinstance(template, str) else template
    template.bind(df)
    groups = by or []
    rows = df.filter(F.col(text).isNotNull())
    if pattern == "fold":
        return _fold(rows, template, reducer, key, text, groups, provenance)
    if pattern != "tree" or fanin < 2:
        raise ValueError("pattern is tree or fold, and fan-in at least 2")
    buckets = buckets or max(64, rows.count() // 50_000)
    bucket, order = partitioner(rows) if partitioner else (F.pmod(F.xxhash64(key), F.lit(buckets)), F.col(key))
    state = rows.select(*groups, bucket.alias("_bucket"), order.alias("_order"), F.col(key).alias("_key"), F.col(text).alias("part"), F.lit(1).cast("bigint").alias("n_sources"), *([F.array(F.col(key)).alias("sources")] if provenance else []))
    state = fit(state, "part", token_budget, overflow).withColumns({"_order": F.struct("_order", "_key", "_piece"), "n_sources": F.when(F.col("_piece") == 0, F.col("n_sources")).otherwise(0)}).drop("_key", "_piece")
    carried = ["n_sources", *(["sources"] if provenance else [])]
    calls, level, loose, merged, before = 0, 0, False, False, 0
    while True:
        state = state.withColumn("_tokens", F.greatest(token_estimate(F.col("part")), F.lit(1)))
        # once packs no longer shrink under the budget, only the fan-in limits them
        state = pack(state, groups, "_bucket", "_order", "_tokens", 2**31 - 1 if loose else token_budget, fanin)
        packs = state.groupBy(*groups, "bin").agg(F.sort_array(F.collect_list(F.struct("_order", "part", *carried))).alias("_rows"))
        packs = packs.select(*groups, "bin", F.col("_rows.part").alias("parts"), F.aggregate("_rows.n_sources", F.lit(0).cast("bigint"), lambda a, b: a + b).alias("n_sources"), *([F.array_sort(F.array_distinct(F.flatten("_rows.sources"))).alias("sources")] if provenance else []))
        partial = reducer.reduce(packs.withColumnRenamed("parts", "_parts"), template, "_parts", "part")
        state = staged(partial.select(*groups, "bin", "part", *carried), "level")
        n = state.count()
        calls += n
        level += 1
        widest = state.groupBy(*groups).count().agg(F.max("count")).first()[0] or 0
        if widest <= 1:
            break
        stuck = level > 1 and n >= before
        if stuck and loose and merged:
            raise RuntimeError("a level of the reduction made no progress")
        loose = loose or stuck
        before = n
        if widest > TOGETHER and not merged and not (level > 1 and stuck):  # go on within buckets; each holds its parts in order
            state = state.select(*groups, F.col("bin.bucket").alias("_bucket"), F.struct("bin.cut", "bin.piece").alias("_order"), "part", *carried)
        elif widest > TOGETHER:  # buckets no longer shrink: neighbours in their order meet in ranges of bounded size
            merged = True
            ranges = max(1, n // max(2 * fanin, TOGETHER // 2))
            spread = state.repartitionByRange(ranges, *groups, "bin").withColumn("_bucket", F.spark_partition_id())
            state = staged(spread.select(*groups, "_bucket", F.col("bin").alias("_order"), "part", *carried), "ranges")
        else:
            number = F.row_number().over(Window.partitionBy(*groups).orderBy("bin")) - 1
            state = state.withColumn("_number", number).select(*groups, F.lit(0).alias("_bucket"), F.col("_number").alias("_order"), "part", *carried)
    return NLResult(state.select(*groups, F.col("part").alias("reduced"), *carried), {"oracle": calls}, {"pattern": "tree", "levels": level})


def _fold(rows: DataFrame, template: Template, reducer: ModelBackend, key: str, text: str, groups: list[str], provenance: bool) -> NLResult:
    """Each group's rows in key order; round n folds the n-th row of every group into its text so far."""
    place = F.row_number().over(Window.partitionBy(*groups).orderBy(key))
    numbered = staged(rows.select(*groups, F.col(key).alias("_key"), F.col(text).alias("_next"), place.alias("_n")), "fold")
    last = numbered.agg(F.max("_n")).first()[0] or 0
    calls = numbered.filter("_n > 1").count()
    first = numbered.filter("_n = 1").select(*groups, F.array("_next").alias("_parts"))
    state = reducer.reduce(first, template, "_parts", "part").select(*groups, "part")
    for n in range(2, last + 1):
        step = numbered.filter(F.col("_n") == n).select(*groups, "_next")
        if groups:
            named = step.withColumnsRenamed({g: f"_of_{g}" for g in groups})
            same = F.lit(True)
            for g in groups:
                same = same & F.col(g).eqNullSafe(F.col(f"_of_{g}"))
            met = state.join(named, same, "left").drop(*[f"_of_{g}" for g in groups])
        else:
            met = state.crossJoin(step)
        met = met.withColumn("_parts", F.when(F.col("_next").isNull(), F.array("part")).otherwise(F.array("part", "_next"))).withColumnRenamed("part", "_so_far")
        state = reducer.reduce(met, template, "_parts", "part")
        state = state.select(*groups, F.when(F.col("_next").isNull(), F.col("_so_far")).otherwise(F.col("part")).alias("part"))
        if n % 8 == 0:
            state = staged(state, "fold")
    sources = numbered.groupBy(*groups).agg(F.count("*").alias("n_sources"), *([F.array_sort(F.collect_list("_key")).alias("sources")] if provenance else []))
    if groups:
        named = sources.withColumnsRenamed({g: f"_of_{g}" for g in groups})
        same = F.lit(True)
        for g in groups:
            same = same & F.col(g).eqNullSafe(F.col(f"_of_{g}"))
        out = state.join(named, same).drop(*[f"_of_{g}" for g in groups])
    else:
        out = state.crossJoin(sources)
    return NLResult(out.select(*groups, F.col("part").alias("reduced"), "n_sources", *(["sources"] if provenance else [])), {"oracle": calls}, {"pattern": "fold"})
