"""Score cuts from a labelled, weighted sample.

``recall_cut`` gives the score at or above which enough of the positives lie,
``precision_cut`` the score at or above which enough of the rows are positive.
``bound="exact"`` uses Beta quantiles at the effective sample size and tests cuts
in a fixed order; ``bound="normal"`` (or ``"subgaussian"``) uses the normal
approximation.  A target that the sample can't certify gives an infinite cut, so
that the oracle decides instead.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from . import bounds

NEVER, ALWAYS = math.inf, -math.inf
#: Candidate cuts among which a precision cut is searched.
CANDIDATES = 10


@dataclass(frozen=True)
class Sample:
    score: np.ndarray
    label: np.ndarray
    weight: np.ndarray

    def __len__(self) -> int:
        return len(self.score)


def positives_needed(target: float, delta: float) -> int:
    """Sampled positives without a miss that certify a recall target."""
    return math.ceil(math.log(delta) / math.log(target))


def recall_cut(sample: Sample, target: float, delta: float, bound: str = "exact") -> float:
    positive = sample.label.astype(bool)
    if not positive.any():
        return ALWAYS
    score, weight = sample.score[positive], sample.weight[positive]
    if bound == "exact":
        n = bounds.effective_size(weight)
        total, best = weight.sum(), ALWAYS
        for cut in np.unique(score):  # from the lowest upward; the first rejection ends it
            share = weight[score >= cut].sum() / total
            if bounds.proportion_lower(share * n, n, delta) < target:
                break
            best = float(cut)
        return best
    cuts = np.unique(score)[::-1]
    shares = np.array([weight[score >= c].sum() for c in cuts]) / weight.sum()
    first = cuts[int(np.argmax(shares >= target - 1e-12))]
    held = sample.weight * sample.label
    upper = bounds.mean_bounds(held * (sample.score >= first), delta / 2, bound)[1]
    lower = max(0.0, bounds.mean_bounds(held * (sample.score < first), delta / 2, bound)[0])
    raised = upper / (upper + lower) if upper + lower > 0 else 1.0
    return float(cuts[int(np.argmax(shares >= min(raised, shares.max()) - 1e-12))])


def candidate_cuts(sample: Sample, count: int = CANDIDATES) -> np.ndarray:
    """Sampled scores at evenly spaced places of the sample, highest first."""
    ordered = np.sort(sample.score)[::-1]
    places = np.unique([max(1, (len(ordered) * i) // count) for i in range(1, count + 1)])
    return np.array([ordered[p - 1] for p in places])


def precision_cut(sample: Sample, target: float, delta: float, bound: str = "exact", count: int = CANDIDATES) -> float:
    """The lowest candidate whose precision is certified; the failure share is divided over the candidates."""
    if not len(sample):
        return NEVER
    best, share = NEVER, delta / count
    for cut in candidate_cuts(sample, count):
        above = sample.score >= cut
        w, y = sample.weight[above], sample.label[above].astype(float)
        p = float((w * y).sum() / w.sum())
        if bound == "exact":
            n = bounds.effective_size(w)
            low = bounds.proportion_lower(p * n, n, share)
        else:
            factor = bounds.z_value(share) if bound == "normal" else math.sqrt(2 * math.log(1 / share))
            low = p - factor * math.sqrt(float((w**2 * (y - p) ** 2).sum())) / float(w.sum())
        if low >= target:
            best = min(best, float(cut))
    return best


def two_cuts(sample: Sample, recall: float | None, precision: float | None, delta: float, bound: str = "exact") -> tuple[float, float]:
    """(lo, hi); with both targets each gets half of the failure probability."""
    share = delta / 2 if recall is not None and precision is not None else delta
    lo = recall_cut(sample, recall, share, bound) if recall is not None else ALWAYS
    if precision is not None:
        hi = precision_cut(sample, precision, share, bound)
    else:
        hi = NEVER
    return lo, max(hi, lo)
