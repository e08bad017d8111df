"""NL top-k: quick-select over pairwise comparisons, and the algorithms it is compared with."""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from functools import total_ordering

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ..models.base import ModelBackend
from ..result import NLResult
from ..staging import staged
from ..stats.hashing import uniform
from ..template import Template

ALGORITHMS = ("quickselect", "quadratic", "heap", "pointwise", "listwise", "rerank", "search")


def _meet(left: DataFrame, right: DataFrame, groups: list[str]) -> DataFrame:
    """Rows of both sides with the same (or null) group values; without groups the right side is one row, or the pair space is wanted."""
    if not groups:
        return left.crossJoin(right)
    named = right.withColumnsRenamed({g: f"_of_{g}" for g in groups})
    same = F.lit(True)
    for g in groups:
        same = same & F.col(g).eqNullSafe(F.col(f"_of_{g}"))
    return left.join(named, same).drop(*[f"_of_{g}" for g in groups])


def _wins_order(rows: DataFrame, template: Template, comparer: ModelBackend, groups: list[str], key: str, k: int | None = None) -> DataFrame:
    """Rows (groups, row) with rank by the number of wins over all others of the group, key on ties; the k best."""
    a = rows.select(*groups, F.col("row").alias("a"))
    b = rows.select(*groups, F.col("row").alias("b"))
    pairs = _meet(a, b, groups).filter(F.col(f"a.{key}") < F.col(f"b.{key}"))
    judged = comparer.better(pairs, template, "a", "b", "_won")
    won = judged.select(*groups, F.when(F.col("_won"), F.col("a")).otherwise(F.col("b")).alias("row"))
    # every row once with no win, so that rows that lost all are counted too
    none = rows.select(*groups, "row", F.lit(0).alias("win"))
    full = won.select(*groups, "row", F.lit(1).alias("win")).unionByName(none).groupBy(*groups, F.col(f"row.{key}").alias("_k")).agg(F.first("row").alias("row"), F.sum("win").alias("wins"))
    order = [F.desc("wins"), F.col(f"row.{key}")]
    if k is not None and not groups:  # only what is in the result meets in one task
        full = full.orderBy(*order).limit(k)
    ranked = full.withColumn("rank", F.row_number().over(Window.partitionBy(*groups).orderBy(*order)))
    return ranked if k is None else ranked.filter(F.col("rank") <= k)


LARGE = 4096  # rows of a group; up to this size all pairs are asked at once
PAIRS_A_TASK = 1 << 24


def _outcomes(few: DataFrame, many: DataFrame, template: Template, comparer: ModelBackend, groups: list[str], key: str, side: str) -> DataFrame:
    """Losses and meetings of each row of one side ("few" or "many") against all rows of the other, itself aside, by (groups, _k).

    A pair is asked in the order of its keys, from whichever side it comes.  The few are shipped whole.
    """
    n = few.count() * many.count()
    tasks = min(10_000, max(many.sparkSession.sparkContext.defaultParallelism, -(-n // PAIRS_A_TASK)))
    left = many.select(*groups, F.col("row").alias("_m")).repartition(tasks, F.col(f"_m.{key}"))
    pairs = _meet(left, F.broadcast(few.select(*groups, F.col("row").alias("_f"))), groups)
    m, f = F.col(f"_m.{key}"), F.col(f"_f.{key}")
    pairs = pairs.filter(m != f).select(*groups, (m if side == "many" else f).alias("_k"), (m < f).alias("_in_order"), F.when(m < f, F.col("_m")).otherwise(F.col("_f")).alias("a"), F.when(m < f, F.col("_f")).otherwise(F.col("_m")).alias("b"))
    judged = comparer.better(pairs, template, "a", "b", "_won")
    many_won = F.coalesce("_won", F.lit(False)) == F.col("_in_order")
    lost = ~many_won if side == "many" else many_won
    return judged.groupBy(*groups, "_k").agg(F.sum(lost.cast("long")).alias("lost"), F.count("*").alias("met"))


def _with_outcomes(rows: DataFrame, outcomes: DataFrame, groups: list[str]) -> DataFrame:
    """Rows with their losses added to those they have."""
    named = outcomes.withColumnsRenamed({g: f"_of_{g}" for g in groups} | {"_k": "_of_k", "lost": "_lost"}).drop("met")
    same = F.col("_k") == F.col("_of_k")
    for g in groups:
        same = same & F.col(g).eqNullSafe(F.col(f"_of_{g}"))
    return rows.join(named, same, "left").withColumn("losses", F.col("losses") + F.coalesce("_lost", F.lit(0))).drop("_of_k", "_lost", *[f"_of_{g}" for g in groups])


def _level(rows: DataFrame, groups: list[str], want) -> DataFrame:
    """For each group the least number of losses that ``want`` rows don't exceed; the rows themselves are not sorted."""
    order = Window.partitionBy(*groups).orderBy("losses")
    levels = rows.groupBy(*groups, "losses").agg(F.count("*").alias("_rows"), F.first(want).alias("_want"))
    return levels.withColumn("_rows", F.sum("_rows").over(order)).filter("_rows >= _want").groupBy(*groups).agg(F.min("losses").alias("level"))


def _best_by_wins(rows: DataFrame, template: Template, comparer: ModelBackend, groups: list[str], key: str, k: int) -> tuple[DataFrame, dict]:
    """The same k rows, wins and ranks as ``_wins_order`` has, of groups too large for all pairs.

    A row that lost more often than the k-th best of any set of rows loses in all can't
    be among the k best by wins, whatever its other answers are.  So a few strong rows meet
    all others, which sets the losses allowed; all rows meet the strongest ones, and those
    within the allowance meet the rest in slices.  Who stays at the end has met every row
    and is ordered by its wins.  Strength is guessed by referees drawn by hash: a bad guess
    costs answers, not rows.  This holds for answers of any kind, noisy or circular ones
    too, that are the same when a pair is asked again.  Groups with an allowance too large
    to leave out much, and groups with repeated or null keys, have all pairs asked.
    """
    sizes = staged(rows.groupBy(*groups).agg(F.count("*").alias("n"), F.count_distinct(f"row.{key}").alias("_keys")), "sizes")
    large = F.expr(f"n > {LARGE} AND n >= {64 * k} AND n = _keys")
    if not k or not sizes.filter(large).count():
        return _wins_order(rows, template, comparer, groups, key, k), {}
    asked = 0

    def outcomes(few, many, side):
        nonlocal asked
        got = staged(_outcomes(few, many, template, comparer, groups, key, side), "outcomes")
        asked += got.agg(F.sum("met")).first()[0] or 0
        return got

    def guess(seed):
        return uniform(F.col("_k"), seed)

    parts = 4 * rows.sparkSession.sparkContext.defaultParallelism
    rest = _meet(rows, sizes.filter(~large).select(*groups), groups) if groups else None
    state = _meet(rows.withColumn("_k", F.col(f"row.{key}")), F.broadcast(sizes.filter(large).select(*groups, "n")), groups)
    state = staged(state.repartition(parts, "_k").withColumn("losses", F.lit(0).cast("long")), "wins")
    referees = staged(state.filter(guess("referee") * F.col("n") < F.greatest(F.lit(256.0), F.sqrt("n") / 4)), "referees")
    scored = staged(_with_outcomes(state, outcomes(referees, state, "many"), groups), "scored")
    strong = F.greatest(F.lit(max(4 * k, 32)), F.least(F.lit(2048), F.expr("n div 16")))
    top = _meet(scored, F.broadcast(_level(scored, groups, strong)), groups).filter("losses <= level").select(*groups, "row", "_k", "n", F.lit(0).cast("long").alias("losses"))
    top = staged(top, "strong")
    place = Window.partitionBy(*groups).orderBy("losses", "_k")
    top = staged(_with_outcomes(top, outcomes(top, top, "many"), groups).withColumn("_place", F.row_number().over(place)), "strong")
    first = staged(top.filter(F.col("_place") <= max(4 * k, 32)), "first")
    bars = outcomes(first, state, "few").groupBy(*groups).agg(F.sort_array(F.collect_list("lost"))[k - 1].alias("allowed"))
    n_top = top.groupBy(*groups).agg(F.count("*").alias("n_top"))
    bars = _meet(bars, n_top, groups).withColumn("_block", F.ceil(1.1 * F.col("allowed") + 4 * F.sqrt("allowed") + 16))
    bars = staged(bars, "bars")
    scored = staged(_meet(scored, F.broadcast(bars), groups), "scored")
    levels = _level(scored, groups, F.least("_block", "n"))
    top_keys = top.select(*groups, "_k", "_place").withColumnsRenamed({"_k": "_of_k"} | {g: f"_of_{g}" for g in groups})
    same = F.col("_k") == F.col("_of_k")
    for g in groups:
        same = same & F.col(g).eqNullSafe(F.col(f"_of_{g}"))
    marked = _meet(scored, F.broadcast(levels), groups).join(F.broadcast(top_keys), same, "left")
    # the order among the strong is the better guess where it reaches far enough
    in_block = F.when(F.col("_block") * 2 <= F.col("n_top"), F.coalesce(F.col("_place") <= F.col("_block"), F.lit(False))).otherwise(F.col("losses") <= F.col("level"))
    marked = staged(marked.select(*groups, "row", "_k", "n", "allowed", F.lit(0).cast("long").alias("losses"), in_block.alias("_in_block")), "marked")
    dense = marked.groupBy(*groups).agg(F.count("*").alias("n"), F.count_if("_in_block").alias("_b")).withColumn("_dense", F.expr("_b * 4 > n"))
    dense = staged(dense.select(*groups, "_dense"), "dense")
    if dense.filter("_dense").count():
        whole = marked.select(*groups, "row") if not groups else _meet(marked, F.broadcast(dense.filter("_dense").select(*groups)), groups).select(*groups, "row")
        rest = whole if rest is None else rest.select(*groups, "row").unionByName(whole)
        if not dense.filter("NOT _dense").count():
            return _wins_order(rows, template, comparer, groups, key, k), {}
        marked = staged(_meet(marked, F.broadcast(dense.filter("NOT _dense").select(*groups)), groups), "marked")
    block = staged(marked.filter("_in_block").select(*groups, "row"), "block")
    after = staged(_with_outcomes(marked, outcomes(block, marked, "many"), groups), "after")
    alive = staged(after.filter("losses <= allowed"), "alive")
    others = after.filter("NOT _in_block")
    if alive.count() <= 32 * k:
        slices = [others]
    else:
        far = others.filter("losses > allowed")
        slices = [others.filter("losses <= allowed")] + [far.filter((guess("slice") >= a) & (guess("slice") < b)) for a, b in ((0.0, 0.25), (0.25, 0.5), (0.5, 1.0))]
    for part in slices:
        alive = staged(_with_outcomes(alive, outcomes(alive, staged(part.select(*groups, "row"), "slice"), "few"), groups).filter("losses <= allowed"), "alive")
    best = alive.select(*groups, F.col("_k"), "row", (F.col("n") - 1 - F.col("losses")).alias("wins"))
    order = [F.desc("wins"), F.col("_k")]
    if not groups:
        best = best.orderBy(*order).limit(k)
    best = best.withColumn("rank", F.row_number().over(Window.partitionBy(*groups).orderBy(*order))).filter(F.col("rank") <= k)
    if rest is not None:
        best = best.unionByName(_wins_order(rest.select(*groups, "row"), template, comparer, groups, key, k), allowMissingColumns=True)
    return best, {"asked_of_large": asked}


def quick_select(df: DataFrame, template: Template, comparer: ModelBackend, k: int, key: str, groups: list[str], pivot: str, similarity: str | None, slack: int, seed: int, final: bool = True) -> NLResult:
    """All groups advance in each round; a group that is settled leaves.

    The survivors of a group meet one pivot.  Only two counts a round reach the driver.
    """
    rows = df.select(*groups, F.struct(*df.columns).alias("row"), *([F.col(similarity).alias("_sim")] if similarity else []))
    state = staged(rows.withColumn("need", F.lit(k)), "rank")
    settled: list[DataFrame] = []
    comparisons, rounds = 0, 0
    while k > 0:
        sizes = state.groupBy(*groups).agg(F.count("*").alias("n"), F.first("need").alias("need"))
        n_rows, n_open = sizes.filter("n > need").agg(F.sum("n"), F.count("*")).first()
        small = _meet(state, sizes.filter("n <= need").select(*groups), groups) if groups else (state if not n_open else None)
        if small is not None:
            settled.append(small.select(*groups, "row"))
        if not n_open:
            break
        comparisons += n_rows - n_open
        rounds += 1
        if groups:
            state = _meet(state, sizes.filter("n > need").select(*groups), groups)
        if rounds == 1 and pivot == "similarity" and similarity:
            place = Window.partitionBy(*groups).orderBy(F.desc("_sim"), F.col(f"row.{key}"))
            if groups:
                ranked = state.withColumn("_p", F.row_number().over(place))
                near = ranked.filter(F.col("_p") <= k + slack).groupBy(*groups).agg(F.max_by("row", "_p").alias("pivot"))
            else:
                near = state.orderBy(F.desc("_sim"), F.col(f"row.{key}")).limit(k + slack).agg(F.min_by("row", F.struct("_sim", -F.col(f"row.{key}"))).alias("pivot"))
        else:
            near = state.groupBy(*groups).agg(F.min_by("row", F.struct(uniform(F.col(f"row.{key}"), f"{seed}/{rounds}"), F.col(f"row.{key}"))).alias("pivot"))
        met = _meet(state, near, groups)
        judged = comparer.better(met, template, "row", "pivot", "_better")
        judged = staged(judged.withColumn("_is_pivot", F.col(f"row.{key}") == F.col(f"pivot.{key}")).withColumn("_better", F.col("_better") & ~F.col("_is_pivot")), "round")
        won = judged.groupBy(*groups).agg(F.sum(F.col("_better").cast("int")).alias("w"))
        full = _meet(judged, won, groups)
        enough = F.col("w") + 1 <= F.col("need")  # winners and pivot are in
        taken = full.filter((enough & (F.col("_better") | F.col("_is_pivot"))) | ((F.col("w") == F.col("need")) & F.col("_better")))
        settled.append(taken.select(*groups, "row"))
        keep = ((F.col("w") > F.col("need")) & F.col("_better")) | ((F.col("w") + 1 < F.col("need")) & ~F.col("_better") & ~F.col("_is_pivot"))
        extra = ["_sim"] if similarity else []
        # the next state reads this round's stage table; it needs no table of its own
        state = full.filter(keep).select(*groups, "row", *extra, F.when(enough, F.col("need") - F.col("w") - 1).otherwise(F.col("need")).alias("need"))
    if not settled:
        best = rows.limit(0).select(*groups, "row")
    else:
        best = settled[0]
        for s in settled[1:]:
            best = best.unionByName(s)
    best = staged(best, "top")
    ordered = _wins_order(best, template, comparer, groups, key) if final else best.withColumn("rank", F.lit(None).cast("int"))
    chosen = best.groupBy(*groups).count().agg(F.sum(F.expr("count * (count - 1) div 2"))).first()[0] or 0
    return NLResult(ordered.select("row.*", "rank"), {"oracle_rounds": comparisons, "oracle_order": chosen if final else 0}, {"algorithm": "quickselect", "pivot": pivot, "rounds": rounds})


def _heap(df: DataFrame, compare: Callable[[dict, dict], bool], k: int, key: str, groups: list[str]) -> NLResult:
    """Heaps of size k within each partition, then one heap over the partitions' survivors for each group."""

    def best(rows: list[dict]) -> tuple[list[dict], int]:
        count = 0

        @total_ordering
        class Held:  # the heap's root is the worst kept row
            def __init__(self, row):
                self.row = row

            def __eq__(self, other):
                return self.row[key] == other.row[key]

            def __lt__(self, other):
                nonlocal count
                count += 1
                return compare(other.row, self.row)

        heap: list = []
        for row in rows:
            if len(heap) < k:
                heapq.heappush(heap, Held(row))
            elif k and Held(heap[0].row) < Held(row):
                heapq.heapreplace(heap, Held(row))
        return [heapq.heappop(heap).row for _ in range(len(heap))][::-1], count

    names = df.columns
    schema = df.schema.simpleString()[len("struct<") : -1]

    def local(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept: dict[tuple, list[dict]] = {}
        counts: dict[tuple, int] = {}
        for batch in batches:
            for row in batch.to_dict("records"):
                kept.setdefault(tuple(row[g] for g in groups), []).append(row)
            for g, rows in kept.items():
                if len(rows) > k:
                    kept[g], n = best(rows)
                    counts[g] = counts.get(g, 0) + n
        for g, rows in kept.items():
            out = pd.DataFrame(rows, columns=names)
            out["_calls"] = [counts.get(g, 0)] + [0] * (len(out) - 1) if len(out) else []
            yield out

    def final(rows: pd.DataFrame) -> pd.DataFrame:
        ordered, n = best(rows.drop(columns=["_calls"]).to_dict("records"))
        out = pd.DataFrame(ordered, columns=names)
        out["rank"] = range(1, len(out) + 1)
        out["_calls"] = [n + int(rows["_calls"].sum())] + [0] * (len(out) - 1) if len(out) else []
        return out

    survivors = df.mapInPandas(local, f"{_ddl(df)}, _calls long")
    out = staged(survivors.groupBy(*groups).applyInPandas(final, f"{_ddl(df)}, rank int, _calls long"), "heap")
    calls = out.agg(F.sum("_calls")).first()[0] or 0
    return NLResult(out.drop("_calls"), {"oracle_heap": calls}, {"algorithm": "heap", "schema": schema})


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def _listwise(df: DataFrame, template: Template, model: ModelBackend | None, order: list, k: int, groups: list[str], key: str, window: int, seed: int) -> NLResult:
    """Windows of rows are ordered by one prompt each (or by a given column); the k best of each window meet in the next round."""
    calls, rounds, state = 0, 0, df
    if k >= window:
        raise ValueError("k must be below the window")
    while True:
        n = state.groupBy(*groups).count().agg(F.max("count")).first()[0] or 0
        last = n <= window
        buckets = max(1, -(-n // window))
        placed = state.withColumn("_b", F.lit(0) if last else F.pmod(F.xxhash64(F.lit(seed + rounds), F.col(key)), F.lit(buckets)))
        if order:
            ranked = placed.withColumn("rank", F.row_number().over(Window.partitionBy(*groups, "_b").orderBy(*order, key))).filter(F.col("rank") <= k)
        else:
            lists = placed.groupBy(*groups, "_b").agg(F.sort_array(F.collect_list(F.struct(key, *[c for c in df.columns if c != key]))).alias("_items"))
            told = model.order(lists, template, "_items", "_ordered").select("_b", F.posexplode(F.slice("_ordered", 1, k)).alias("_at", "_row"))
            ranked = staged(told.select(*[F.col(f"_row.{c}").alias(c) for c in df.columns], "_b", (F.col("_at") + 1).cast("int").alias("rank")), "ordered")
        calls += placed.select(*groups, "_b").distinct().count()
        rounds += 1
        if last:
            return NLResult(ranked.drop("_b"), {"oracle_lists": calls}, {"algorithm": "listwise", "rounds": rounds})
        state = staged(ranked.drop("_b", "rank"), "lists")


def nl_rank(
    df: DataFrame,
    template: str | Template,
    k: int,
    comparer: ModelBackend | None = None,
    *,
    key: str,
    by: list[str] | None = None,
    algorithm: str = "quickselect",
    pivot: str = "random",
    similarity: str | None = None,
    slack: int | None = None,
    score: str | None = None,
    compare: Callable[[dict, dict], bool] | None = None,
    retrieve: int = 100,
    window: int = 20,
    seed: int = 0,
) -> NLResult:
    """The k best rows, with their rank (1 is best), for each value of ``by``.

    ``similarity`` names a column that orders rows by closeness to the ranking text;
    with ``pivot="similarity"`` the row in place k + slack of that order is the first
    pivot, which changes the number of comparisons but not the result.  ``score`` names
    a score column for the pointwise, listwise and re-ranking algorithms; without it the
    model is asked (its score for each row, or its order of each window).  Heaps compare
    one pair at a time: by ``compare``, a Python function, or by the model's ``decide``.
    """
    template = Template(template) if isinstance(template, str) else template
    groups = by or []
    if not isinstance(df.schema[key].dataType, LongType):
        df = df.withColumn(key, F.col(key).cast("long"))
    if algorithm == "quickselect":
        slack = max(1, -(-k // 10)) if slack is None else slack
        return quick_select(df, template, comparer, k, key, groups, pivot, similarity, slack, seed)
    if algorithm == "quadratic":
        rows = df.select(*groups, F.struct(*df.columns).alias("row"))
        calls = df.groupBy(*groups).count().agg(F.sum(F.expr("count * (count - 1) div 2"))).first()[0] or 0
        best, notes = _best_by_wins(rows, template, comparer, groups, key, k)
        # the algorithm's calls; plan["asked_of_large"] says how many settled its result in large groups
        return NLResult(best.select("row.*", "rank"), {"oracle_pairs": calls}, {"algorithm": algorithm, **notes})
    if algorithm == "heap":
        if compare is None:
            compare = lambda a, b: comparer.decide(template, a, b)
        return _heap(df, compare, k, key, groups)
    if algorithm == "pointwise" and score is None:
        columns = df.columns
        told = staged(comparer.score(df, template, "_score"), "scores")  # each row is asked about once
        best = nl_rank(told, template, k, key=key, by=by, algorithm="pointwise", score="_score")
        return NLResult(best.df.select(*columns, "rank"), best.calls, best.plan)
    order = {"pointwise": [F.desc(score)] if score else [], "search": [F.desc(similarity)] if similarity else []}
    if algorithm in ("pointwise", "search"):
        place = Window.partitionBy(*groups).orderBy(*order[algorithm], key)
        if not groups:  # a global top-k without a global window
            best = df.orderBy(*order[algorithm], key).limit(k)
            return NLResult(best.withColumn("rank", F.row_number().over(place)), {"oracle_scores" if algorithm == "pointwise" else "embedding": df.count()}, {"algorithm": algorithm})
        return NLResult(df.withColumn("rank", F.row_number().over(place)).filter(F.col("rank") <= k), {"oracle_scores" if algorithm == "pointwise" else "embedding": df.count()}, {"algorithm": algorithm})
    if algorithm == "listwise":
        return _listwise(df, template, comparer, [F.desc(score)] if score else [], k, groups, key, window, seed)
    if algorithm == "rerank":
        first = nl_rank(df, template, retrieve, key=key, by=by, algorithm="search", similarity=similarity).df.drop("rank")
        return nl_rank(staged(first, "retrieved"), template, k, comparer, key=key, by=by, algorithm="pointwise", score=score)
    raise ValueError(f"algorithm is one of {ALGORITHMS}")
