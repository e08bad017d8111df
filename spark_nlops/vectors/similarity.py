"""Vector arithmetic on array columns, and blocked similarity of two tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..staging import staged

#: Bytes of vectors in a block: a right side up to this size is shipped whole.
BLOCK_BYTES = 64_000_000


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double"))), F.lit(0.0), lambda s, x: s + x))


def _matrix(vectors: pd.Series, dim: int) -> np.ndarray:
    return np.stack([np.asarray(v, dtype=float) for v in vectors]) if len(vectors) else np.zeros((0, dim))


def block_product(left: DataFrame, right: DataFrame, run: Callable[[pd.DataFrame, np.ndarray, np.ndarray], Iterator[pd.DataFrame]], schema: str, dims: int = 1, combine: Callable[[list[pd.DataFrame]], pd.DataFrame] = lambda frames: pd.concat(frames, ignore_index=True)) -> DataFrame:
    """``run`` over all pairs of a part of the left side and a block of the right one (keys, matrix), whatever their sizes.

    ``left`` has lk and vector columns, ``right`` k and v; keys are integers.  A right
    side of at most ``BLOCK_BYTES`` is shipped whole, and left rows stay where they
    are.  Beyond that both sides are dealt to blocks of that size on the executors,
    and block pairs meet by their numbers: the driver sees two counts, and the plan
    doesn't grow with the data.
    """
    right = staged(right.filter("v IS NOT NULL"), "right")
    n, dim = right.agg(F.count("*"), F.max(F.size("v"))).first()
    dim = dim or 0
    blocks = max(1, -(-n * dim * 8 // BLOCK_BYTES))
    if blocks == 1:
        rows = right.toPandas().sort_values("k", kind="stable")
        shipped = left.sparkSession.sparkContext.broadcast((rows["k"].to_numpy(dtype=np.int64), _matrix(rows["v"], dim)))

        def whole(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            keys, matrix = shipped.value
            for batch in batches:
                found = [x for a in range(0, len(batch) if len(keys) else 0, 512) for x in run(batch.iloc[a : a + 512], keys, matrix)]
                if found:
                    yield combine(found)

        return left.mapInPandas(whole, schema)
    left = staged(left, "left")
    lefts = max(1, -(-left.count() * dims * dim * 8 // BLOCK_BYTES))
    a = left.withColumns({"i": F.pmod(F.xxhash64("lk"), F.lit(lefts)).cast("int"), "j": F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))})
    b = right.withColumns({"j": F.pmod(F.xxhash64("k"), F.lit(blocks)).cast("int"), "i": F.explode(F.sequence(F.lit(0), F.lit(lefts - 1)))})

    def cell(l: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:
        r = r.sort_values("k", kind="stable")
        keys, matrix = r["k"].to_numpy(dtype=np.int64), _matrix(r["v"], dim)
        found = [x for at in range(0, len(l) if len(keys) else 0, 512) for x in run(l.iloc[at : at + 512], keys, matrix)]
        return combine(found) if found else pd.DataFrame(columns=[c.split()[0] for c in schema.split(", ")])

    return a.groupBy("i", "j").cogroup(b.groupBy("i", "j")).applyInPandas(cell, schema)


def _sides(left: DataFrame, right: DataFrame, left_key: str, left_vec: str, right_key: str, right_vec: str) -> tuple[DataFrame, DataFrame]:
    return (
        left.select(F.col(left_key).cast("long").alias("lk"), F.col(left_vec).alias("v")).filter("v IS NOT NULL"),
        right.select(F.col(right_key).cast("long").alias("k"), F.col(right_vec).alias("v")),
    )


def similar_pairs(left: DataFrame, right: DataFrame, left_key: str, left_vec: str, right_key: str, right_vec: str, *, least: float | None = None, k: int | None = None) -> DataFrame:
    """(left_key, right_key, sim) as lk, rk, sim: pairs of at least ``least``, or each left row's k best (smaller right key on ties).

    Of each block only what can still be in the result leaves the Arrow batch.
    """
    if (least is None) == (k is None):
        raise ValueError("give either least or k")

    def run(part: pd.DataFrame, keys: np.ndarray, matrix: np.ndarray) -> Iterator[pd.DataFrame]:
        sims = np.round(_matrix(part["v"], matrix.shape[1]) @ matrix.T, 9)
        if k is not None:
            order = np.argsort(-sims, axis=1, kind="stable")[:, :k]
            i, j = np.repeat(np.arange(len(part)), order.shape[1]), order.reshape(-1)
        else:
            i, j = np.nonzero(sims >= least)
        yield pd.DataFrame({"lk": part["lk"].to_numpy()[i], "rk": keys[j], "sim": sims[i, j]})

    out = block_product(*_sides(left, right, left_key, left_vec, right_key, right_vec), run, "lk long, rk long, sim double")
    if k is not None:
        best = Window.partitionBy("lk").orderBy(F.desc("sim"), "rk")
        out = out.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)
    return out


def score_histogram(left: DataFrame, right: DataFrame, left_key: str, left_vec: str, right_key: str, right_vec: str, bins: int = 10_000) -> np.ndarray:
    """Counts of all pairs' similarities in equal bins of [-1, 1]; pairs are never rows."""

    def run(part: pd.DataFrame, keys: np.ndarray, matrix: np.ndarray) -> Iterator[pd.DataFrame]:
        sims = np.clip(np.round(_matrix(part["v"], matrix.shape[1]) @ matrix.T, 9), -1, 1)
        at, n = np.unique(np.minimum(((sims + 1) / 2 * bins).astype(int).reshape(-1), bins - 1), return_counts=True)
        yield pd.DataFrame({"bin": at, "n": n})

    total = np.zeros(bins, dtype=np.int64)
    found = block_product(*_sides(left, right, left_key, left_vec, right_key, right_vec), run, "bin int, n long", combine=lambda frames: pd.concat(frames).groupby("bin", as_index=False)["n"].sum())
    for r in found.groupBy("bin").agg(F.sum("n").alias("n")).collect():  # at most ``bins`` rows
        total[r["bin"]] += r["n"]
    return total


def bucketed_pairs(left: DataFrame, right: DataFrame, left_key: str, left_vec: str, right_key: str, right_vec: str, *, least: float, dim: int, tables: int = 12, planes: int = 8, seed: int = 1) -> DataFrame:
    """Pairs of at least ``least`` that share a random-hyperplane bucket in one of several tables: an approximate join for sides too large for blocks.

    The chance to miss a pair of cosine c is (1 - (1 - acos(c)/pi)^planes)^tables;
    every row is in every table, and pairs are verified exactly.
    """
    from .index import hyperplane_bucket

    def listed(df: DataFrame, key: str, vec: str, k: str, v: str) -> DataFrame:
        codes = F.array(*[F.struct(F.lit(t).alias("t"), hyperplane_bucket(F.col(vec).cast("array<double>"), dim, planes, seed * 1000 + t).alias("b")) for t in range(tables)])
        return df.filter(F.col(vec).isNotNull()).select(F.col(key).cast("long").alias(k), F.col(vec).alias(v), F.explode(codes).alias("slot"))

    met = listed(left, left_key, left_vec, "lk", "lv").join(listed(right, right_key, right_vec, "rk", "rv"), "slot")
    return met.withColumn("sim", F.round(cosine(F.col("lv"), F.col("rv")), 9)).filter(F.col("sim") >= least).select("lk", "rk", "sim").distinct()
