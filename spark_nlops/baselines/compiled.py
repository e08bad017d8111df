"""A compiled multi-step label pipeline: guess labels, retrieve, re-rank."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..operators.join import pair_rows
from ..operators.project import nl_project
from ..operators.search import nl_similar_join
from ..template import Template
from ..vectors.embed import Embedder


def guess_retrieve_rerank(left: DataFrame, right: DataFrame, template: str, *, left_key: str, right_key: str, right_text: str, projector: ModelBackend, projection: str, embedder: Embedder, reranker: ModelBackend, k: int = 10, retrieve: int = 20) -> DataFrame:
    """lk, rk and rank: the k best right rows of each left row."""
    guessed = nl_project(left, projection, "_guess", projector)
    near = nl_similar_join(guessed, right, "_guess", right_text, retrieve, left_key=left_key, right_key=right_key, embedder=embedder)
    t = Template(template)
    pairs = pair_rows(left, right, t, left_key, right_key, near.filter("right_key IS NOT NULL").select(F.col("left_key").alias("lk"), F.col("right_key").alias("rk"), "sim"))
    scored = reranker.score(pairs, t, "_s")
    order = Window.partitionBy("lk").orderBy(F.desc("_s"), F.desc("sim"), "rk")
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("lk", "rk", "rank")
