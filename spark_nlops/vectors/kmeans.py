"""Deterministic k-means over array columns: hashed start, Lloyd rounds as one small aggregation each."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..stats.hashing import uniform


def nearest_center(vec: Column, centers: list[list[float]]) -> Column:
    """Struct (d, c) of the nearest centre, the lower number on ties; null vectors give null. The centres are a small broadcast table."""
    m = np.asarray(centers, dtype=float)

    @F.pandas_udf("d double, c int")
    def near(vectors: pd.Series) -> pd.DataFrame:
        d, c = [None] * len(vectors), [None] * len(vectors)
        given = [i for i, v in enumerate(vectors) if v is not None]
        for a in range(0, len(given), 4096):
            rows = given[a : a + 4096]
            x = np.stack([np.asarray(vectors.iloc[i], dtype=float) for i in rows])
            far = np.stack([np.round(np.sqrt(((x - center) ** 2).sum(axis=1)), 9) for center in m], axis=1)
            best = far.argmin(axis=1)
            for i, j, value in zip(rows, best.tolist(), far[np.arange(len(rows)), best].tolist()):
                d[i], c[i] = value, j
        return pd.DataFrame({"d": pd.Series(d, dtype=float), "c": pd.Series(c, dtype="Int32")})

    return near(vec)


def first_centers(df: DataFrame, key: str, vec: str, c: int, seed: int) -> list[list[float]]:
    """Farthest-point start: the row of least hash, then each time the row farthest from all centres so far."""
    first = df.orderBy(uniform(F.col(key), seed), key).select(vec).limit(1).collect()
    centers = [list(map(float, r[0])) for r in first]
    while centers and len(centers) < c:
        far = df.select(vec, key, nearest_center(F.col(vec), centers)["d"].alias("d")).orderBy(F.desc("d"), key).limit(1).collect()[0]
        if far["d"] == 0:
            break  # fewer distinct rows than centres
        centers.append(list(map(float, far[0])))
    return centers


def lloyd_step(df: DataFrame, vec: str, centers: list[list[float]]) -> list[list[float]]:
    """Means of the rows nearest to each centre; a centre without rows stays."""
    own = df.select(F.col(vec).alias("v"), nearest_center(F.col(vec), centers)["c"].alias("c"))
    dims = [F.avg(F.element_at("v", i + 1).cast("double")).alias(f"d{i}") for i in range(len(centers[0]))]
    out = [list(c) for c in centers]
    for r in own.groupBy("c").agg(*dims).collect():  # one row for each centre
        out[r["c"]] = [round(r[f"d{i}"], 9) for i in range(len(centers[0]))]
    return out


def vector_kmeans(df: DataFrame, key: str, vec: str, c: int, *, seed: int = 0, rounds: int = 20) -> tuple[DataFrame, list[list[float]]]:
    """All columns with cluster and dist, and the centres."""
    centers = first_centers(df, key, vec, c, seed)
    if not centers:
        return df.withColumns({"cluster": F.lit(None).cast("int"), "dist": F.lit(None).cast("double")}), []
    for _ in range(rounds):
        moved = lloyd_step(df, vec, centers)
        if np.allclose(moved, centers, atol=1e-9):
            break
        centers = moved
    near = nearest_center(F.col(vec), centers)
    return df.withColumn("_near", near).withColumns({"cluster": F.col("_near.c"), "dist": F.col("_near.d")}).drop("_near"), centers
