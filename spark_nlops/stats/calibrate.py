"""Quantile re-scaling of proxy scores to (0, 1]."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..staging import staged


#: A score with a larger share of all rows is hot: at most its inverse many are, and their rows are spread.
HOT_SHARE = 0.005

#: Steps of the quantile function that is read off a sketch.
STEPS = 200


def _steps_up_to(x, points: list[float], low: int, high: int):
    """How many of the sorted points are up to x, as nested comparisons of logarithmic depth."""
    if low == high:
        return F.lit(low)
    mid = (low + high) // 2
    return F.when(x >= points[mid], _steps_up_to(x, points, mid + 1, high)).otherwise(_steps_up_to(x, points, low, mid))


def quantile_scale(df: DataFrame, score: str, out: str = "scaled", *, mode: str = "exact", k: int = 800) -> DataFrame:
    """``exact``: the share of rows with a score up to this one; ``sketch``: the same from a KLL sketch of fixed size.

    Exact ranks need no global window: distinct scores are counted, range
    partitioned, summed within partitions, and the partitions' totals (one number
    each) are carried over.  Null scores stay null.  Rows of a hot score (a share above
    ``HOT_SHARE``) meet as many copies of its rank as shuffles have partitions.
    """
    if mode == "sketch":
        # the quantile function is read off the sketch on a fixed grid and becomes a literal step function
        grid = F.array(*[F.lit(i / STEPS) for i in range(STEPS + 1)])
        cut = df.agg(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double(F.col(score).cast("double"), F.lit(k)), grid)).first()[0]
        if cut is None:
            return df.withColumn(out, F.lit(None).cast("double"))
        # the share of grid points up to the score, by binary search over the sorted grid
        points = sorted(float(x) for x in cut)
        x = F.col(score).cast("double")
        return df.withColumn(out, F.when(x.isNotNull(), _steps_up_to(x, points, 0, len(points)) / F.lit(float(len(points)))))
    if mode != "exact":
        raise ValueError("mode is exact or sketch")
    counts = df.filter(F.col(score).isNotNull()).groupBy(F.col(score).alias("_value")).agg(F.count("*").alias("n"))
    placed = staged(counts.repartitionByRange("_value").withColumn("part", F.spark_partition_id()), "ranks")
    totals = {r["part"]: r["n"] for r in placed.groupBy("part").agg(F.sum("n").alias("n")).collect()}  # one number for each partition
    if not totals:
        return df.withColumn(out, F.lit(None).cast("double"))
    running, offsets = 0, []
    for part in sorted(totals):
        offsets += [F.lit(part), F.lit(running)]
        running += totals[part]
    within = F.sum("n").over(Window.partitionBy("part").orderBy("_value").rowsBetween(Window.unboundedPreceding, 0))
    ranks = placed.select("_value", ((within + F.element_at(F.create_map(*offsets), F.col("part"))) / F.lit(float(running))).alias(out))
    hot = [r["_value"] for r in placed.filter(F.col("n") > HOT_SHARE * running).select("_value").collect()]  # at most 1 / HOT_SHARE
    if not hot:
        return df.join(ranks, df[score] == ranks["_value"], "left").drop("_value")
    copies = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")))
    dealt = df.withColumn("_copy", F.when(F.col(score).isin(hot), F.pmod(F.monotonically_increasing_id(), F.lit(copies))).otherwise(F.lit(0)).cast("int"))
    ranks = ranks.withColumn("_copy", F.explode(F.when(F.col("_value").isin(hot), F.sequence(F.lit(0), F.lit(copies - 1))).otherwise(F.array(F.lit(0)))))
    return dealt.join(ranks, (dealt[score] == ranks["_value"]) & (dealt["_copy"] == ranks["_copy"]), "left").drop("_value", "_copy")
