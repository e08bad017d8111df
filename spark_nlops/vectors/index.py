"""Text indices on disk: vectors by bucket and a manifest."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..staging import staged
from .embed import Embedder


def hyperplane_bucket(vec: Column, dim: int, planes: int, seed: int = 5) -> Column:
    """Sign pattern of the vector against seeded random hyperplanes, as an integer below 2^planes; null vectors give null."""
    normals = np.random.default_rng(seed).standard_normal((planes, dim)).round(6)
    powers = 1 << np.arange(planes)

    @F.pandas_udf("int")
    def bucket(vectors: pd.Series) -> pd.Series:
        out = [None] * len(vectors)
        given = [i for i, v in enumerate(vectors) if v is not None]
        for a in range(0, len(given), 4096):
            rows = given[a : a + 4096]
            x = np.stack([np.asarray(vectors.iloc[i], dtype=float) for i in rows])
            for i, code in zip(rows, ((x @ normals.T >= 0) @ powers).tolist()):
                out[i] = code
        return pd.Series(out, dtype="Int32")

    return bucket(vec)


def build_text_index(df: DataFrame, key: str, text: str, embedder: Embedder, path: str, *, planes: int = 4) -> None:
    """Embed a column once and store key and vector, partitioned by bucket; every row is indexed."""
    vectors = embedder.embed(df.select(F.col(key).cast("long").alias("key"), F.coalesce(text, F.lit("")).alias("text")), "text", "vec")
    vectors = staged(vectors, "index")  # embedded once
    dim = vectors.agg(F.max(F.size("vec"))).first()[0] or embedder.dim  # of the data: not every embedder knows it beforehand
    bucketed = vectors.select("key", "vec", hyperplane_bucket(F.col("vec"), dim, planes).alias("bucket"))
    bucketed.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/vectors")
    stamp = df.agg(F.count("*").alias("rows"), F.sum(F.xxhash64(key, text).cast("decimal(38,0)")).cast("string").alias("hash")).first()
    manifest = {"embedder": embedder.embedder_id, "dim": dim, "metric": "cosine", "planes": planes, "rows": stamp["rows"], "hash": stamp["hash"], "key": key, "text": text}
    df.sparkSession.createDataFrame([(json.dumps(manifest),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


class TextIndex:
    def __init__(self, vectors: DataFrame, manifest: dict) -> None:
        self.vectors, self.manifest = vectors, manifest

    def matches(self, df: DataFrame) -> bool:
        """Whether the index was built from these rows."""
        m = self.manifest
        stamp = df.agg(F.count("*"), F.sum(F.xxhash64(m["key"], m["text"]).cast("decimal(38,0)")).cast("string")).first()
        return (stamp[0], stamp[1]) == (m["rows"], m["hash"])

    def probe(self, query: list[float], flips: int = 1) -> DataFrame:
        """Rows of the query's bucket and of buckets that differ in up to ``flips`` planes; partitions are pruned."""
        from itertools import combinations

        planes = self.manifest["planes"]
        spark = self.vectors.sparkSession
        own = spark.createDataFrame([(query,)], "vec array<double>").select(hyperplane_bucket(F.col("vec"), self.manifest["dim"], planes)).first()[0]
        near = {own ^ sum(1 << i for i in c) for n in range(flips + 1) for c in combinations(range(planes), n)}
        return self.vectors.filter(F.col("bucket").isin(sorted(near)))


def load_text_index(spark: SparkSession, path: str) -> TextIndex:
    manifest = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    return TextIndex(spark.read.parquet(f"{path}/vectors"), manifest)
