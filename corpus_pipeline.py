"""A corpus pipeline of five stages, each written as Parquet and read again by the next.

Language ID drops documents whose language can't be told with confidence; SimHash
keeps the first document of each near-duplicate group (fingerprints of three
words within two bits, or a similarity of 0.8 in sets of five words); suffix intervals cut
repeated passages out of the texts; string tiling drops documents that hold
benchmark items; byte-level BPE turns what is left into token ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spark_nlops.llm import bpe, langid, simhash, suffix_dedup, tiling
from spark_nlops.llm.common import Stage, free_name, read_table

#: Least calibrated probability of the predicted language.
LEAST_CONFIDENCE = 0.5

#: No stage but the first filter can be written in SQL, so the rows are tested against brute force.
ORACLE_SQL = None


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is told with confidence.

    Null and empty texts and texts without a letter go; null keys are judged by
    their texts; repeated rows are judged alike; very long texts are read whole;
    other columns, whatever their names, stay; an empty table gives an empty one.
    """
    model = langid.train(langid.learnable(docs))
    told = free_name(docs, "nlops_language")
    out = langid.predict(docs, model, out=told)
    return out.filter((F.col(f"{told}.lang") != langid.UNDETERMINED) & (F.col(f"{told}.score") >= LEAST_CONFIDENCE)).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group: the one of the smallest doc_id, null ones last; of several with that doc_id, the first one.

    Null and empty texts are one group; very long texts are compared whole; other
    columns, whatever their names, stay; an empty table gives an empty one.
    """
    odd = docs.groupBy("doc_id").count().filter("doc_id IS NULL OR count > 1").limit(1).count()
    if not odd:
        found = simhash.duplicate_groups(docs)
        return docs.join(found.filter("component <> doc_id").select("doc_id").distinct(), "doc_id", "left_anti").select(*docs.columns)
    # rows get a number of their own, written once so that it holds
    number = free_name(docs, "nlops_row")
    rows = Stage(spark, "rows").keep(docs.withColumn(number, F.monotonically_increasing_id()), "rows")
    found = simhash.duplicate_groups(rows, key=number).join(rows.select(number, F.col("doc_id").cast("long").alias("id")), number)
    first = found.groupBy("component").agg(F.min(F.struct(F.col("id").isNull(), "id", number))[number].alias(number))
    gone = found.join(first, number, "left_anti").select(number)
    return rows.join(gone, number, "left_anti").select(*docs.columns)


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, their texts without bytes that a string of 200 bytes repeats elsewhere; whole characters only, n_chars counted anew.

    Null texts stay null; repeated rows are copies of each other and lose all such
    bytes; null keys are treated like any others; texts of any length are read
    whole; other columns, whatever their names, stay; an empty table gives an empty one.
    """
    cut = suffix_dedup.without_repeats(docs)
    return cut.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text").cast("long"))).select(*docs.columns)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item to the threshold.

    Null and empty texts hold none and stay; repeated rows and null keys are judged
    by their texts; very long texts are read whole; other columns, whatever their
    names, stay; an empty table gives an empty one, and an empty benchmark drops nothing.
    """
    leak = free_name(docs, "nlops_leak")
    found = tiling.contamination(docs, read_table(spark, sf_dir, "benchmark"), null_items=True, out=leak)
    return found.filter(F.size(leak) == 0).select(*docs.columns)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, digests and ids of every document; null and empty texts have no ids, repeated rows are encoded each, an empty table gives an empty one."""
    return bpe.encode_documents(docs)


STAGES = [
    ("language_id", identify_language),
    ("simhash_near_dedup", drop_near_duplicates),
    ("suffix_array_dedup", cut_repeated_passages),
    ("benchmark_decontamination", drop_benchmark_leaks),
    ("byte_bpe_encoding", encode_tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    stage = Stage(spark, "pipeline")
    docs = read_table(spark, sf_dir, "documents")
    for n, (name, function) in enumerate(STAGES):
        docs = stage.keep(function(spark, docs, sf_dir), name)
        if n:
            stage.drop(STAGES[n - 1][0])
    return docs
