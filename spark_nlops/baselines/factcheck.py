"""Claim verification programs: hand-written, row-wise, and with NL operators.

A claim is supported if some retrieved document contains it.  Every program maps a
claim to two queries (its halves), retrieves documents for them, and judges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..models.base import ModelBackend
from ..operators.filter import nl_filter
from ..operators.search import nl_similar_join
from ..result import NLResult, SampleSpec
from ..staging import staged
from ..vectors.embed import Embedder

VERDICT = "claim {claim} is supported by {context}"


def claim_queries(claims: DataFrame) -> DataFrame:
    """claim_id, query_no (0, 1), query: the first and the second half of the words."""
    w = F.split("claim", r"\s+")
    half = F.ceil(F.size(w) / 2).cast("int")
    halves = F.array(F.array_join(F.slice(w, F.lit(1), half), " "), F.array_join(F.slice(w, half + 1, F.greatest(F.size(w) - half, F.lit(1))), " "))
    return claims.select("claim_id", F.posexplode(halves).alias("query_no", "query"))


def retrieved(claims: DataFrame, corpus: DataFrame, embedder: Embedder, k: int) -> DataFrame:
    """claim_id, claim, doc_ids and context (texts of the distinct documents found for both queries, by id)."""
    queries = claim_queries(claims).withColumn("query_id", F.col("claim_id") * 2 + F.col("query_no"))
    found = nl_similar_join(queries, corpus, "query", "text", k, left_key="query_id", right_key="doc_id", embedder=embedder)
    hits = found.filter("right_key IS NOT NULL").select(F.floor(F.col("left_key") / 2).alias("claim_id"), F.col("right_key").alias("doc_id")).distinct()
    texts = hits.join(corpus.select("doc_id", "text"), "doc_id").groupBy("claim_id").agg(F.sort_array(F.collect_list(F.struct("doc_id", "text"))).alias("_d"))
    return claims.join(texts, "claim_id", "left").select("claim_id", "claim", F.coalesce(F.col("_d.doc_id"), F.array().cast("array<bigint>")).alias("doc_ids"), F.coalesce(F.array_join("_d.text", "\n"), F.lit("")).alias("context"))


def operator_program(claims: DataFrame, corpus: DataFrame, embedder: Embedder, oracle: ModelBackend, k: int, proxy: ModelBackend | None = None, **targets) -> NLResult:
    """Map, search, filter; the filter as reference plan or cascade."""
    evidence = staged(retrieved(claims, corpus, embedder, k), "evidence")
    sample = targets.pop("sample", SampleSpec())
    return nl_filter(evidence, VERDICT, oracle, proxy=proxy, key="claim_id", sample=sample, **targets)


def rowwise_program(claims: DataFrame, corpus: DataFrame, embedder: Embedder, model: ModelBackend, k: int) -> DataFrame:
    """Map, search, map; the last map's text is parsed."""
    from .rowwise import rowwise_filter

    return rowwise_filter(retrieved(claims, corpus, embedder, k), VERDICT, model)


def handwritten_pipeline(claims: DataFrame, corpus: DataFrame, embedder: Embedder, oracle: ModelBackend, k: int) -> DataFrame:
    """Five stages, one after the other, each finished for all claims before the next begins."""
    extracted = staged(claims.select("claim_id", F.trim("claim").alias("claim")), "extracted")
    evidence = staged(retrieved(extracted, corpus, embedder, k), "evidence")
    from ..template import Template

    judged = staged(oracle.label(evidence, Template(VERDICT), "_label"), "judged")
    return judged.filter("_label").select(*evidence.columns)
