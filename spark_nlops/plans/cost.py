"""Call counts of plans before they run."""

from __future__ import annotations

import math


def filter_calls(n: int, sample: int, band: int, plan: str) -> int:
    return {"reference": n, "proxy_only": 0, "cascade": min(n, sample + band)}[plan]


def join_calls(n1: int, n2: int, sample: int, band: int, plan: str) -> int:
    return {"reference": n1 * n2, "direct": sample + band, "projected": sample + band + n1}[plan]


def rank_calls(n: int, k: int, algorithm: str, window: int = 20) -> float:
    """Exact for the quadratic, pointwise and search algorithms, expected order of size for the others."""
    return {
        "quadratic": n * (n - 1) / 2,
        "heap": n + k * math.log(max(n, 2)) * max(1.0, math.log2(max(k, 2))),
        "quickselect": 3.0 * n + k * (k - 1) / 2,
        "pointwise": n,
        "listwise": n / window * (1 + 1 / max(1, window - 1)),
        "search": 0,
    }[algorithm]


def reduce_calls(n: int, fanin: int, pattern: str) -> int:
    if pattern == "fold":
        return max(0, n - 1)
    total = 0
    while n > 1:
        n = -(-n // fanin)
        total += n
    return total
