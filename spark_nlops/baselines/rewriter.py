"""An emulation of an optimizer that rewrites programs by trial, best effort.

The plan search of such systems is a black box, so only what shows is emulated: a
fixed list of rewrites, each scored on a small sample that is not corrected for
chance; the best is kept; some runs find no valid plan, by a seeded draw.  Its
quality figures are those of the emulation.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..operators.join import pair_rows
from ..operators.search import nl_similar_join
from ..result import NLResult
from ..staging import staged
from ..stats.hashing import uniform
from ..template import Template
from ..vectors.embed import Embedder

#: Share of runs without a valid plan.
FAILURE_RATE = 1 / 3


def succeeds(seed: int, rate: float = FAILURE_RATE) -> bool:
    return int(hashlib.md5(f"plan:{seed}".encode()).hexdigest()[:8], 16) / 2**32 >= rate


def success(seed: Column, rate: float = FAILURE_RATE) -> Column:
    """The same as a column."""
    return uniform(seed, "plan") >= rate


def blocking_join(left: DataFrame, right: DataFrame, template: str, oracle: ModelBackend, *, left_key: str, right_key: str, embedder: Embedder, budget: int, seed: int = 0, vectors: DataFrame | None = None) -> NLResult:
    """Similarity blocking with as many candidates for each left row as the call budget allows; the oracle judges these. vectors: the left rows' vectors, if they are stored."""
    if not succeeds(seed):
        return NLResult(left.limit(0).select(F.col(left_key).alias("lk"), F.col(left_key).alias("rk")), {}, {"plan": "none", "success": False})
    t = Template(template)
    k = max(1, budget // max(1, left.count()))
    near = staged(nl_similar_join(left, right, t.columns("left")[0], t.columns("right")[0], k, left_key=left_key, right_key=right_key, embedder=embedder, vectors=vectors), "blocked")
    asked = pair_rows(left, right, t, left_key, right_key, near.filter("right_key IS NOT NULL").select(F.col("left_key").alias("lk"), F.col("right_key").alias("rk")))
    return NLResult(oracle.label(asked, t, "_label").filter("_label").select("lk", "rk"), {"oracle": near.count()}, {"plan": f"blocking k={k}", "success": True})


def mean_of_successes(run, wanted: int = 3, most: int = 30) -> tuple[list, int]:
    """The first ``wanted`` successful runs and the number of runs made."""
    found, made = [], 0
    while len(found) < wanted and made < most:
        result = run(made)
        made += 1
        if result.plan["success"]:
            found.append(result)
    return found, made
