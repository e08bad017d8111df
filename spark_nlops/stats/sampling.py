"""Hashed samples: uniform, or Poisson with weights mixed with uniform ones."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..result import SampleSpec
from .hashing import uniform


def inclusion_probability(score: Column, total_weight: float, n: int, size: int, spec: SampleSpec) -> Column:
    """min(1, size * ((1 - mix) * score^power / sum + mix / n))."""
    weight = F.pow(score, F.lit(spec.weight_power))
    share = (F.lit(1 - spec.uniform_mix) * weight / F.lit(total_weight) if total_weight > 0 else F.lit(0.0)) + F.lit(spec.uniform_mix / max(n, 1))
    if total_weight <= 0:
        share = F.lit(1.0 / max(n, 1))
    return F.least(F.lit(1.0), F.lit(float(size)) * share)


def weighted_sample(df: DataFrame, score: str, key: str, spec: SampleSpec) -> tuple[DataFrame, int]:
    """Sampled rows with their inclusion probability ``pi``, and the number of rows of df."""
    n, total = df.agg(F.count("*"), F.sum(F.pow(F.col(score), F.lit(spec.weight_power)))).first()
    pi = inclusion_probability(F.col(score), float(total or 0.0), n, spec.size(n), spec)
    return df.withColumn("pi", pi).filter(uniform(F.col(key), spec.seed) < F.col("pi")), n


def uniform_sample(df: DataFrame, key: str, spec: SampleSpec) -> tuple[DataFrame, int]:
    n = df.count()
    rate = min(1.0, spec.size(n) / max(n, 1))
    return df.withColumn("pi", F.lit(rate)).filter(uniform(F.col(key), spec.seed) < F.lit(rate)), n


def _poisson_count(u: pd.Series, rate: pd.Series) -> pd.Series:
    """The least k whose cumulative Poisson probability exceeds u, for rates of any size; null for nulls."""

    def invert(x: float, r: float) -> int | None:
        if np.isnan(x) or np.isnan(r):
            return None
        if r <= 0:
            return 0
        width = 12 * math.sqrt(r) + 40  # beyond it the probability is lost in a double
        k = np.arange(max(0, math.floor(r - width)), math.ceil(r + width))
        steps = np.log(r / np.maximum(k, 1))
        steps[0] = k[0] * math.log(r) - r - math.lgamma(k[0] + 1)
        return int(k[min(np.searchsorted(np.cumsum(np.exp(np.cumsum(steps))), x, side="right"), len(k) - 1)])

    return pd.Series([invert(x, r) for x, r in zip(u, rate)], dtype="Int32")


def draw_with_replacement(df: DataFrame, score: str, key: str, spec: SampleSpec) -> DataFrame:
    """Times each row is drawn in ``size`` draws, approximated row by row by a Poisson count from one hashed uniform."""
    n, total = df.agg(F.count("*"), F.sum(F.pow(F.col(score), F.lit(spec.weight_power)))).first()
    rate = F.lit(float(spec.size(n))) * (F.lit(1 - spec.uniform_mix) * F.pow(score, F.lit(spec.weight_power)) / F.lit(max(float(total or 0), 1e-300)) + F.lit(spec.uniform_mix / max(n, 1)))
    u = uniform(F.col(key), spec.seed)
    draws = F.pandas_udf(_poisson_count, "int")(u, rate)
    return df.withColumn("draws", draws).withColumn("rate", rate).filter("draws > 0")
