"""Confidence bounds for means and proportions."""

from __future__ import annotations

import math
from statistics import NormalDist

import numpy as np


def z_value(delta: float) -> float:
    return NormalDist().inv_cdf(1 - delta)


def _beta_fraction(a: float, b: float, x: float) -> float:
    tiny = 1e-300
    c, d = 1.0, 1.0 / max(1 - (a + b) * x / (a + 1), tiny)
    out = d
    for m in range(1, 400):
        for term in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + term * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + term / c
            c = c if abs(c) > tiny else tiny
            out *= c * d
        if abs(c * d - 1) < 1e-13:
            break
    return out


def beta_cdf(x: float, a: float, b: float) -> float:
    if x <= 0:
        return 0.0
    if x >= 1:
        return 1.0
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x < (a + 1) / (a + b + 2):
        return front * _beta_fraction(a, b, x) / a
    return 1 - front * _beta_fraction(b, a, 1 - x) / b


def beta_quantile(p: float, a: float, b: float) -> float:
    low, high = 0.0, 1.0
    for _ in range(80):
        mid = (low + high) / 2
        if beta_cdf(mid, a, b) < p:
            low = mid
        else:
            high = mid
    return (low + high) / 2


def proportion_lower(successes: float, n: float, delta: float) -> float:
    """Exact (Clopper-Pearson) lower bound; n may be an effective sample size."""
    if n <= 0 or successes <= 0:
        return 0.0
    return beta_quantile(delta, successes, n - successes + 1)


def proportion_upper(successes: float, n: float, delta: float) -> float:
    return 1 - proportion_lower(n - successes, n, delta)


def mean_bounds(values: np.ndarray, delta: float, bound: str = "normal") -> tuple[float, float]:
    """Lower and upper bound of a mean, each at delta."""
    n = len(values)
    if not n:
        return -math.inf, math.inf
    mean = float(values.mean())
    if bound == "hoeffding":  # values in [0, max]
        width = float(values.max()) * math.sqrt(math.log(1 / delta) / (2 * n))
    else:
        factor = z_value(delta) if bound == "normal" else math.sqrt(2 * math.log(1 / delta))
        width = factor * float(values.std()) / math.sqrt(n)
    return mean - width, mean + width


def effective_size(weights: np.ndarray) -> float:
    total = float((weights**2).sum())
    return float(weights.sum()) ** 2 / total if total else 0.0
