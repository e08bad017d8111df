"""Similarity search and similarity join over embeddings or a stored index."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..staging import staged
from ..template import Template
from ..vectors.embed import Embedder
from ..vectors.index import TextIndex
from ..vectors.similarity import cosine, similar_pairs


def with_similarity(df: DataFrame, text: str, query: str, embedder: Embedder, out: str = "sim") -> DataFrame:
    """All columns and the cosine to a query text, rounded so that ties are ties everywhere."""
    asked = embedder.embed(df.sparkSession.createDataFrame([(query,)], "t string"), "t", "v").first()["v"]
    own = embedder.embed(df.withColumn("_t", F.coalesce(text, F.lit(""))), "_t", "_v")
    return own.withColumn(out, F.round(cosine(F.col("_v"), F.array(*[F.lit(float(x)) for x in asked])), 9)).drop("_v", "_t")


def nl_search(df: DataFrame, text: str, query: str, k: int, *, key: str, embedder: Embedder, index: TextIndex | None = None, rerank: int | None = None, reranker: ModelBackend | None = None, template: str | Template | None = None) -> DataFrame:
    """The k rows closest to a query, with sim and rank; with a re-ranker, the best ``rerank`` of them by its score."""
    if index is None:
        found = with_similarity(df, text, query, embedder)
    else:
        asked = embedder.embed(df.sparkSession.createDataFrame([(query,)], "t string"), "t", "v").first()["v"]
        near = index.vectors.select(F.col("key").alias("_k"), F.round(cosine(F.col("vec"), F.array(*[F.lit(float(x)) for x in asked])), 9).alias("sim"))
        found = df.join(near.orderBy(F.desc("sim"), "_k").limit(k), F.col(key) == F.col("_k")).drop("_k")
    best = found.orderBy(F.desc("sim"), key).limit(k)
    order = [F.desc("sim"), F.col(key)]
    if rerank is not None:
        scored = staged(reranker.score(best, Template(template) if isinstance(template, str) else template, "rerank_score"), "retrieved")
        best, order = scored.orderBy(F.desc("rerank_score"), key).limit(rerank), [F.desc("rerank_score"), F.col(key)]
    return best.withColumn("rank", F.row_number().over(Window.orderBy(*order)))  # at most k rows


def embedded(df: DataFrame, text: str, key: str, embedder: Embedder) -> DataFrame:
    """The key and the text's vector, vec; a missing text is an empty one."""
    return embedder.embed(df.select(key, F.coalesce(text, F.lit("")).alias("_t")), "_t", "vec").drop("_t")


def nl_similar_join(left: DataFrame, right: DataFrame, left_on: str, right_on: str, k: int, *, left_key: str, right_key: str, embedder: Embedder, index: TextIndex | None = None, vectors: DataFrame | None = None) -> DataFrame:
    """Each left row with its k closest right rows: left key, right key, sim and rank (left rows without a match keep nulls).

    ``vectors`` has the left key and vec, the embedder's vectors of all left rows, where they are stored already (``embedded``).
    """
    own = (embedded(left, left_on, left_key, embedder) if vectors is None else vectors).withColumnRenamed("vec", "_v")
    if index is not None:
        other, other_key, other_vec = index.vectors, "key", "vec"
    else:
        other, other_key, other_vec = embedder.embed(right.select(right_key, F.coalesce(right_on, F.lit("")).alias("_t")), "_t", "_v"), right_key, "_v"
    found = similar_pairs(own, other, left_key, "_v", other_key, other_vec, k=k)
    keys = left.select(F.col(left_key).cast("long").alias("left_key"))
    return keys.join(found.withColumnRenamed("lk", "left_key"), "left_key", "left").select("left_key", F.col("rk").alias("right_key"), "sim", "rank")
