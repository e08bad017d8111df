"""Row-wise AI functions only: map, search and similarity join; nothing works across rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import MODELLED_SECONDS_PER_CALL, extrapolate
from ..models.base import ModelBackend
from ..operators.join import pair_rows
from ..operators.project import nl_project
from ..template import Template


def rowwise_filter(df: DataFrame, template: str, model: ModelBackend) -> DataFrame:
    """A map whose text is parsed as a verdict; text that is no verdict counts as false."""
    said = nl_project(df, template, "_verdict", model)
    return said.filter(F.lower(F.trim("_verdict")).startswith("true")).drop("_verdict")


def rowwise_join(left: DataFrame, right: DataFrame, template: str, model: ModelBackend, left_key: str, right_key: str) -> DataFrame:
    """Every pair is mapped to a verdict text and parsed."""
    pairs = pair_rows(left, right, Template(template), left_key, right_key)
    said = model.text(pairs, Template(template), "_verdict")
    return said.filter(F.lower(F.trim("_verdict")).startswith("true")).select("lk", "rk")


def rowwise_join_cost(left: DataFrame, right: DataFrame) -> DataFrame:
    """Calls and modelled seconds of the nested loop, without running it."""
    counts = left.agg(F.count("*").alias("n1")).crossJoin(right.agg(F.count("*").alias("n2")))
    return counts.select((F.col("n1") * F.col("n2")).alias("calls"), F.round(F.col("n1") * F.col("n2") * F.lit(MODELLED_SECONDS_PER_CALL), 3).alias("modelled_sec"))


def rowwise_rank(df: DataFrame, score: str, k: int, key: str) -> DataFrame:
    """A score for each row, then a sort."""
    return df.orderBy(F.desc(score), key).limit(k)


__all__ = ["extrapolate", "rowwise_filter", "rowwise_join", "rowwise_join_cost", "rowwise_rank"]
