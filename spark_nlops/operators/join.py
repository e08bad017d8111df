"""NL join: nested loop, two embedding-based cascades, and the choice between them."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..plans import budget
from ..result import NLResult, SampleSpec
from ..staging import staged
from ..stats import cuts
from ..template import Template
from ..vectors.containment import FEW, containment_candidates, containment_groups
from ..vectors.embed import Embedder
from ..vectors.similarity import block_product, score_histogram, similar_pairs
from .filter import route


def pair_rows(left: DataFrame, right: DataFrame, template: Template, left_key: str, right_key: str, pairs: DataFrame | None = None, right_first: bool = False) -> DataFrame:
    """lk, rk and the template's columns as left_* and right_*, of all pairs or of the given ones (lk, rk); the side joined first moves with the pairs."""
    l = left.select(F.col(left_key).alias("lk"), *[F.col(c).alias(f"left_{c}") for c in template.columns("left")])
    r = right.select(F.col(right_key).alias("rk"), *[F.col(c).alias(f"right_{c}") for c in template.columns("right")])
    if pairs is None:
        return l.crossJoin(r)
    return pairs.join(r, "rk").join(l, "lk") if right_first else pairs.join(l, "lk").join(r, "rk")


def finish(left: DataFrame, right: DataFrame, matched: DataFrame, left_key: str, right_key: str, kind: str) -> DataFrame:
    """Matched keys as an inner, left, semi or anti join; right columns get the prefix right_."""
    if kind in ("semi", "anti"):
        return left.join(matched.select(F.col("lk").alias(left_key)).distinct(), left_key, f"left_{kind}")
    named = right.select(*[F.col(c).alias(f"right_{c}") for c in right.columns])
    how = {"inner": "inner", "left": "left"}[kind]
    tied = left.join(matched.select(F.col("lk").alias(left_key), F.col("rk").alias("_rk")), left_key, how)
    return tied.join(named, F.col("_rk") == F.col(f"right_{right_key}"), how).drop("_rk")


def _every_pair(left: DataFrame, right: DataFrame, template: Template, oracle: ModelBackend, left_key: str, right_key: str) -> DataFrame:
    """The pairs (lk, rk) for which the template is true, every pair being judged.

    A rule that only holds where a left text contains a right one is not shown pairs that
    can't, and copies of a right text share an answer if it sees nothing else of them.
    """
    holds = getattr(oracle, "holds", None)
    if holds is None:
        asked, copies = pair_rows(left, right, template, left_key, right_key), None
    else:
        text, part = (c.removeprefix(p) for c, p in zip(holds, ("left_", "right_")))
        if template.columns("right") == [part]:
            pairs, copies = containment_groups(left, right, left_key, text, right_key, part)
        else:
            pairs, copies = containment_candidates(left, right, left_key, text, right_key, part), None
        pairs = staged(pairs, "asked")
        few = pairs.count() <= FEW  # else texts move, and parts are the shorter ones
        asked = pair_rows(left, right, template, left_key, right_key, F.broadcast(pairs) if few else pairs, right_first=not few)
    matched = oracle.label(asked, template, "_label").filter("_label").select("lk", "rk")
    return matched if copies is None else staged(matched.withColumnRenamed("rk", "first"), "told").join(copies, "first").select("lk", "rk")


@dataclass
class JoinPlanReport:
    name: str
    lo: float
    hi: float
    band: int
    accepted: int
    sample: int
    projections: int

    @property
    def oracle_calls(self) -> int:
        return self.band + self.sample + self.projections


def _above(histogram: np.ndarray, cut: float) -> int:
    """Pairs with similarity of at least a cut that lies on a bin border."""
    if cut == cuts.ALWAYS:
        return int(histogram.sum())
    if cut == cuts.NEVER:
        return 0
    return int(histogram[int(round((cut + 1) / 2 * len(histogram))) :].sum())


def _on_border(cut: float, bins: int) -> float:
    """A cut lowered to a bin border, so that histogram counts are exact."""
    if not np.isfinite(cut):
        return cut
    return float(np.floor((cut + 1) / 2 * bins) / bins * 2 - 1)


def pair_sample(left: DataFrame, right: DataFrame, vecs: list[str], histograms: list[np.ndarray], left_key: str, right_key: str, spec: SampleSpec, n: int) -> DataFrame:
    """A Poisson sample of pairs (lk, rk, pi, s0, s1, ...), weighted by an even mixture of all plans' quantiles and uniform."""
    bins = len(histograms[0])
    # weight of a pair under one plan: its quantile to the power, from the histogram
    tables = []
    for h in histograms:
        q = np.cumsum(h) / max(h.sum(), 1)
        w = q**spec.weight_power
        tables.append(w / max((w * h).sum(), 1e-300))
    size, mix, seed = float(spec.size(n)), spec.uniform_mix, spec.seed
    salt = np.uint64(int(hashlib.md5(str(seed).encode()).hexdigest()[:15], 16))

    def run(part: pd.DataFrame, keys: np.ndarray, matrix: np.ndarray) -> Iterator[pd.DataFrame]:
        sims = [np.clip(np.round(np.stack([np.asarray(v, float) for v in part[f"v{i}"]]) @ matrix.T, 9), -1, 1) for i in range(len(tables))]
        share = np.full(sims[0].shape, mix / n)
        for s, t in zip(sims, tables):
            share += (1 - mix) / len(tables) * t[np.minimum(((s + 1) / 2 * bins).astype(int), bins - 1)]
        pi = np.minimum(1.0, size * share)
        # a cheap seeded draw keeps few pairs; it is a hash of the pair, not a generator
        lk = part["lk"].to_numpy(dtype=np.int64)
        h = (lk[:, None].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) ^ (keys[None, :].astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)) ^ salt
        for _ in range(2):
            h ^= h >> np.uint64(31)
            h *= np.uint64(0xD6E8FEB86659FD93)
        i, j = np.nonzero((h >> np.uint64(11)) / float(2**53) < pi)
        yield pd.DataFrame({"lk": lk[i], "rk": keys[j], "pi": pi[i, j]} | {f"s{x}": s[i, j] for x, s in enumerate(sims)})

    slim = left.select(F.col(left_key).cast("long").alias("lk"), *[F.col(v).alias(f"v{i}") for i, v in enumerate(vecs)])
    schema = "lk long, rk long, pi double, " + ", ".join(f"s{i} double" for i in range(len(vecs)))
    return block_product(slim, right.select(F.col(right_key).cast("long").alias("k"), F.col("vec").alias("v")), run, schema, len(vecs))


def choose_join_plan(reports: list[JoinPlanReport]) -> JoinPlanReport:
    """The plan of fewest oracle calls; the first on ties."""
    return min(reports, key=lambda r: r.oracle_calls)


def nl_join(
    left: DataFrame,
    right: DataFrame,
    template: str | Template,
    oracle: ModelBackend,
    *,
    left_key: str,
    right_key: str,
    how: str = "inner",
    plan: str = "reference",
    embedder: Embedder | None = None,
    projector: ModelBackend | None = None,
    projection: str | Template | None = None,
    recall: float | None = None,
    precision: float | None = None,
    delta: float = 0.2,
    bound: str = "exact",
    strict: bool = False,
    sample: SampleSpec | None = None,
    bins: int = 10_000,
) -> NLResult:
    """Pairs for which the template is true; keys are integers.

    ``reference``: every pair is asked.  ``direct``: pair scores are similarities of the
    two sides' embeddings.  ``projected``: the left side is first mapped, one call for
    each row, towards the right side's domain.  ``auto``: both are planned on one
    labelled sample and the one of fewer calls runs.
    """
    template = Template(template) if isinstance(template, str) else template
    template.bind_pair(left, right)
    n1, n2 = left.count(), right.count()
    if plan == "reference" or n1 * n2 == 0:
        matched = _every_pair(left, right, template, oracle, left_key, right_key)
        return NLResult(finish(left, right, matched, left_key, right_key, how), {"oracle": n1 * n2}, {"plan": "reference"})
    if recall is None and precision is None and (own := budget.current()) is not None:
        recall, precision, delta = own.recall, own.precision, own.delta
    if embedder is None or (recall is None and precision is None):
        raise ValueError("a cascade needs an embedder and a target")
    spec = sample or SampleSpec()
    names = {"direct": ["direct"], "projected": ["projected"], "auto": ["direct", "projected"]}[plan]
    text_l, text_r = template.columns("left")[0], template.columns("right")[0]
    right_v = staged(embedder.embed(right.select(right_key, F.coalesce(text_r, F.lit("")).alias("_t")), "_t", "vec").drop("_t"), "right")
    own, vecs = F.coalesce(text_l, F.lit("")).alias("_t"), []
    if "projected" in names:
        wanted = Template(projection) if isinstance(projection, str) else (projection or Template("{" + text_l + "}"))
        left_v = projector.text(left, wanted, "_guess").select(left_key, own, F.coalesce("_guess", F.lit("")).alias("_guess"))
    else:
        left_v = left.select(left_key, own)
    if "direct" in names:
        left_v = embedder.embed(left_v, "_t", "vec_direct")
        vecs.append("vec_direct")
    if names == ["direct", "projected"]:  # a guess that is the text itself has its vector
        other = embedder.embed(left_v.withColumns({"_same": F.col("_guess") == F.col("_t"), "_other": F.when(F.col("_guess") == F.col("_t"), F.lit("")).otherwise(F.col("_guess"))}), "_other", "_vec_other")
        left_v = other.withColumn("vec_projected", F.when(F.col("_same"), F.col("vec_direct")).otherwise(F.col("_vec_other")))
        vecs.append("vec_projected")
    elif "projected" in names:
        left_v = embedder.embed(left_v, "_guess", "vec_projected")
        vecs.append("vec_projected")
    left_v = staged(left_v.select(left_key, *vecs), "left")
    histograms = [score_histogram(left_v, right_v, left_key, v, right_key, "vec", bins) for v in vecs]
    drawn = pair_sample(left_v, right_v, vecs, histograms, left_key, right_key, spec, n1 * n2)
    drawn = pair_rows(left, right, template, left_key, right_key, staged(drawn, "pairs"))
    answers = staged(oracle.label(drawn, template, "_label").filter("_label IS NOT NULL").select("lk", "rk", "pi", "_label", *[f"s{i}" for i in range(len(vecs))]), "labels")
    rows = answers.toPandas().sort_values(["lk", "rk"])
    share = delta / 2 if strict and len(names) > 1 else delta
    reports = []
    for i, name in enumerate(names):
        labelled = cuts.Sample(rows[f"s{i}"].to_numpy(float), rows["_label"].to_numpy(float), 1 / rows["pi"].to_numpy(float))
        lo, hi = cuts.two_cuts(labelled, recall, precision, share, bound)
        lo = _on_border(lo, bins)
        hi = hi if not np.isfinite(hi) else max(lo, float(np.ceil((hi + 1) / 2 * bins - 1e-9) / bins * 2 - 1))
        accepted = _above(histograms[i], hi)
        reports.append(JoinPlanReport(name, lo, hi, _above(histograms[i], lo) - accepted, accepted, len(rows), n1 if name == "projected" else 0))
    chosen = choose_join_plan(reports)
    if chosen.oracle_calls >= n1 * n2:  # never dearer than asking every pair
        out = nl_join(left, right, template, oracle, left_key=left_key, right_key=right_key, how=how)
        out.calls = {"oracle": n1 * n2, "oracle_sample": len(rows)}
        out.plan = {"plan": "reference", "why": "the cascade can't be certified for less", "reports": reports}
        return out
    least = chosen.lo if np.isfinite(chosen.lo) else -1.0
    pairs = similar_pairs(left_v, right_v, left_key, vecs[names.index(chosen.name)], right_key, "vec", least=least)
    routed = staged(pairs.withColumn("_route", route(F.col("sim"), chosen.lo, chosen.hi)), "routed")
    band = routed.filter("_route = 'ask'").select("lk", "rk")
    told = band.join(answers.select("lk", "rk", "_label"), ["lk", "rk"])  # labels of the sample are not asked for again
    middle = pair_rows(left, right, template, left_key, right_key, band.join(answers.select("lk", "rk"), ["lk", "rk"], "left_anti"))
    asked = staged(oracle.label(middle, template, "_label").filter("_label").select("lk", "rk"), "matched")
    matched = asked.unionByName(told.filter("_label").select("lk", "rk")).unionByName(routed.filter("_route = 'accept'").select("lk", "rk"))
    counts = {r["_route"]: r["n"] for r in routed.groupBy("_route").agg(F.count("*").alias("n")).collect()}
    calls = {"oracle_sample": len(rows), "oracle_band": counts.get("ask", 0), "oracle_projection": chosen.projections, "accept": counts.get("accept", 0), "embedding": n1 * len(vecs) + n2}
    return NLResult(finish(left, right, matched, left_key, right_key, how), calls, {"plan": chosen.name, "lo": chosen.lo, "hi": chosen.hi, "reports": reports, "reused": told.count()})


