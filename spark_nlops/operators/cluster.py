"""NL group-by: discovery of labels, point-wise classification, and its cascade."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..plans import budget
from ..result import NLResult, SampleSpec
from ..staging import staged
from ..stats import cuts, sampling
from ..template import Template
from ..vectors.embed import Embedder
from ..vectors.kmeans import vector_kmeans
from ..vectors.similarity import cosine
from .reduce import nl_reduce


def discover_groups(df: DataFrame, template: str | Template, groups: int, *, key: str, projector: ModelBackend, embedder: Embedder, reducer: ModelBackend, shown: int = 10, seed: int = 0) -> tuple[DataFrame, list[str], NLResult]:
    """Candidate label of each row, its vector and cluster; the label of each cluster.

    Distinct candidates are embedded once and joined back.
    """
    template = Template(template) if isinstance(template, str) else template
    named = staged(projector.text(df, template.bind(df), "candidate"), "candidates")
    distinct = named.filter("candidate IS NOT NULL").select("candidate").distinct()
    vectors = staged(embedder.embed(distinct, "candidate", "vec"), "vectors")
    placed = named.join(vectors, "candidate")
    clustered, centers = vector_kmeans(placed, key, "vec", groups, seed=seed)
    clustered = staged(clustered, "clustered")
    near = Window.partitionBy("cluster").orderBy("dist", key)
    shown_rows = clustered.withColumn("_place", F.row_number().over(near)).filter(F.col("_place") <= shown)
    labels = nl_reduce(shown_rows.select("cluster", key, "candidate"), "{candidate}", reducer, key=key, text="candidate", by=["cluster"], fanin=max(2, shown))
    found = {r["cluster"]: r["reduced"] for r in labels.df.collect()}  # one for each cluster
    calls = {"oracle_projection": named.count(), "oracle_labels": labels.calls["oracle"]}
    return clustered, [found.get(i, "") for i in range(len(centers))], NLResult(labels.df, calls, {"centers": len(centers)})


def nl_classify(
    df: DataFrame,
    template: str | Template,
    labels: list[str],
    oracle: ModelBackend,
    *,
    key: str | None = None,
    text: str | None = None,
    embedder: Embedder | None = None,
    centers: dict[str, list[float]] | None = None,
    vec: str | None = None,
    accuracy: float | None = None,
    delta: float = 0.2,
    plan: str = "auto",
    bound: str = "exact",
    sample: SampleSpec | None = None,
) -> NLResult:
    """All rows with ``group_label``.

    ``reference`` asks the oracle about every row.  The cascade takes the label whose
    centre is nearest where the similarity is above a cut at which a uniform sample
    certifies the accuracy, and asks the oracle elsewhere.  ``proxy_only`` always
    takes the nearest.
    """
    template = Template(template) if isinstance(template, str) else template
    template.bind(df)
    columns = df.columns
    if accuracy is None and (share := budget.current()) is not None:
        accuracy, delta = share.accuracy, share.delta
    if plan == "reference" or (plan == "auto" and accuracy is None):
        return NLResult(oracle.classify(df, template, labels, "group_label"), {"oracle": df.count()}, {"plan": "reference"})
    spark = df.sparkSession
    if centers is None:
        rows = embedder.embed(spark.createDataFrame([(k,) for k in labels], "k string"), "k", "v").collect()
        centers = {r["k"]: list(r["v"]) for r in rows}
    own = df if vec else embedder.embed(df.withColumn("_t", F.coalesce(text, F.lit(""))), "_t", "_v").drop("_t")
    v = F.col(vec or "_v")
    scored = F.array(*[F.struct((-F.round(cosine(v, F.array(*[F.lit(float(x)) for x in centers[k]])), 9)).alias("s"), F.lit(k).alias("k")) for k in sorted(labels)])
    placed = staged(own.withColumn("_best", F.array_min(scored)).withColumns({"_sim": -F.col("_best.s"), "_near": F.col("_best.k")}).drop("_best", "_v"), "placed")
    if plan == "proxy_only":
        return NLResult(placed.select(*columns, F.col("_near").alias("group_label")), {"embedding": placed.count()}, {"plan": plan})
    drawn, n = sampling.uniform_sample(placed, key, sample or SampleSpec())
    answers = staged(oracle.classify(drawn, template, labels, "_truth").select(key, "_sim", "_near", "_truth"), "labels")
    rows = answers.toPandas().sort_values(key)
    correct = (rows["_near"] == rows["_truth"]).to_numpy(float)
    cut = cuts.precision_cut(cuts.Sample(rows["_sim"].to_numpy(float), correct, np.ones(len(rows))), accuracy, delta, bound)
    sure = F.col("_sim") >= F.lit(cut) if np.isfinite(cut) else F.lit(False)
    routed = placed.withColumn("_sure", F.coalesce(sure, F.lit(False)))
    known = answers.filter("_truth IS NOT NULL").select(F.col(key).alias("_k"), F.col("_truth").alias("group_label"))
    open_rows = routed.filter("NOT _sure")
    told = open_rows.join(known, F.col(key) == F.col("_k"))  # answers of the sample are not asked for again
    asked = oracle.classify(open_rows.join(known.select("_k"), F.col(key) == F.col("_k"), "left_anti"), template, labels, "group_label")
    out = routed.filter("_sure").select(*columns, F.col("_near").alias("group_label")).unionByName(asked.select(*columns, "group_label")).unionByName(told.select(*columns, "group_label"))
    band = open_rows.count()
    return NLResult(out, {"embedding": n, "oracle_sample": len(rows), "oracle_band": band, "accept": n - band}, {"plan": "cascade", "cut": cut, "reused": told.count()})


def nl_cluster(df: DataFrame, template: str | Template, groups: int, *, key: str, projector: ModelBackend, embedder: Embedder, reducer: ModelBackend, oracle: ModelBackend, labels: list[str] | None = None, accuracy: float | None = None, delta: float = 0.2, sample: SampleSpec | None = None, seed: int = 0) -> NLResult:
    """Group labels are discovered, or given, and every row gets one."""
    if labels is not None:
        text = (Template(template) if isinstance(template, str) else template).columns()[0]
        return nl_classify(df, template, labels, oracle, key=key, text=text, embedder=embedder, accuracy=accuracy, delta=delta, sample=sample)
    clustered, found, notes = discover_groups(df, template, groups, key=key, projector=projector, embedder=embedder, reducer=reducer, seed=seed)
    labels = sorted({x for x in found if x})
    # the candidates' vectors of the discovery serve again
    out = nl_classify(clustered, template, labels, oracle, key=key, vec="vec", embedder=embedder, accuracy=accuracy, delta=delta, sample=sample)
    out.calls |= notes.calls
    out.plan["labels"] = labels
    return out


def grouping_objective(df: DataFrame, scores: dict[str, str]) -> DataFrame:
    """Sum over rows of the best label's score; scores maps labels to SQL expressions."""
    best = F.array_max(F.array(*[F.expr(s).cast("double") for s in scores.values()]))
    return df.agg(F.sum(best).alias("objective"), F.count("*").alias("n_rows"))
