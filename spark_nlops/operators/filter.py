"""NL filter: the reference plan and the proxy cascade."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..plans import budget
from ..result import NLResult, SampleSpec
from ..staging import staged
from ..stats import calibrate, cuts, sampling
from ..template import Template


def route(score: Column, lo: float, hi: float) -> Column:
    """accept at hi or above, ask from lo up to hi, reject below; infinite cuts are allowed."""
    accept = score >= F.lit(hi) if np.isfinite(hi) else F.lit(hi == cuts.ALWAYS)
    ask = score >= F.lit(lo) if np.isfinite(lo) else F.lit(lo == cuts.ALWAYS)
    return F.when(accept, "accept").when(ask, "ask").otherwise("reject")


def labelled_sample(scored: DataFrame, template: Template, oracle: ModelBackend, key: str, spec: SampleSpec, score: str = "scaled") -> tuple[cuts.Sample, int, DataFrame]:
    """The oracle's labels of a weighted sample (bounded by the spec), on the driver in key order; the table's rows; and the labels (key, _label) as a stage table."""
    drawn, n = sampling.weighted_sample(scored, score, key, spec)
    answers = staged(oracle.label(drawn, template, "_label").filter("_label IS NOT NULL").select(key, score, "pi", "_label"), "labels")
    rows = answers.toPandas().sort_values(key, kind="stable")
    sample = cuts.Sample(rows[score].to_numpy(float), rows["_label"].to_numpy(dtype=float), 1 / rows["pi"].to_numpy(float) if len(rows) else np.zeros(0))
    return sample, n, answers.select(key, "_label")


def nl_filter(
    df: DataFrame,
    template: str | Template,
    oracle: ModelBackend,
    *,
    proxy: ModelBackend | None = None,
    key: str | None = None,
    recall: float | None = None,
    precision: float | None = None,
    delta: float = 0.2,
    plan: str = "auto",
    bound: str = "exact",
    calibration: str = "exact",
    sample: SampleSpec | None = None,
) -> NLResult:
    """Rows for which the template is true.

    ``plan="reference"`` asks the oracle about every row.  ``"auto"`` with a proxy and
    a target scores all rows with the proxy, learns two cuts from a labelled sample,
    accepts above the upper one, rejects below the lower one and asks the oracle in
    between; the sample's labels are used again there, so ``key`` has to name each row
    once.  ``"proxy_only"`` takes the proxy's own labels.  Rows with a null slot are
    not in the result.
    """
    template = Template(template) if isinstance(template, str) else template
    template.bind(df)
    columns = df.columns
    if recall is None and precision is None and (share := budget.current()) is not None:
        recall, precision, delta = share.recall, share.precision, share.delta
    if plan == "proxy_only":
        labelled = proxy.label(df, template, "_label")
        return NLResult(labelled.filter("_label").select(*columns), {"proxy": df.count()}, {"plan": plan})
    if plan == "reference" or proxy is None or (recall is None and precision is None):
        asked = df.filter(~template.has_null())
        return NLResult(oracle.label(asked, template, "_label").filter("_label").select(*columns), {"oracle": asked.count()}, {"plan": "reference"})
    if key is None:
        raise ValueError("a cascade needs a key column, for its sample")
    spec = sample or SampleSpec()
    scored = proxy.score(df, template, "_score").filter("_score IS NOT NULL")
    scored = staged(calibrate.quantile_scale(scored, "_score", "_scaled", mode=calibration) if calibration != "none" else scored.withColumn("_scaled", F.col("_score")), "scored")
    drawn, n, answers = labelled_sample(scored, template, oracle, key, spec, "_scaled")
    lo, hi = cuts.two_cuts(drawn, recall, precision, delta, bound)
    routed = scored.withColumn("_route", route(F.col("_scaled"), lo, hi))
    counts = {r["_route"]: r["n"] for r in routed.groupBy("_route").agg(F.count("*").alias("n")).collect()}
    band = routed.filter("_route = 'ask'")
    told = band.join(answers, key)  # labels of the sample are not asked for again
    asked = oracle.label(band.join(answers.select(key), key, "left_anti"), template, "_label")
    middle = asked.filter("_label").select(*columns).unionByName(told.filter("_label").select(*columns))
    out = routed.filter("_route = 'accept'").select(*columns).unionByName(middle)
    calls = {"proxy": n, "oracle_sample": len(drawn), "oracle_band": counts.get("ask", 0), "accept": counts.get("accept", 0), "reject": counts.get("reject", 0)}
    notes = {"plan": "cascade", "lo": lo, "hi": hi, "bound": bound, "sampled_positives": int(drawn.label.sum()) if len(drawn) else 0, "reused": told.count()}
    if lo == cuts.ALWAYS and recall is not None:
        needed = cuts.positives_needed(recall, delta / 2 if precision is not None else delta)
        notes["why"] = f"the sample has {notes['sampled_positives']} positives; a recall of {recall} needs about {needed} without a miss"
    return NLResult(out, calls, notes)
