"""Token counts of flat token files without an index.

A flat file is a sequence of token ids in which an end-of-document id closes each
document; nothing says where documents begin.  Files are held as blocks of fixed
length that ignore document borders.  Each block is searched for separators in one
vectorised pass, which leaves a summary (length, number of separators, tokens
before the first and after the last one) and the lengths of the documents within.
A prefix scan over the summaries of a file stitches the documents that cross
block borders and numbers all documents.

Only summaries are put in order; the scan of a file takes one small row for each
block, never its tokens.

Defined results: two separators in a row make a document of no tokens; tokens
after the last separator make a last, unterminated document; a file without
tokens has no documents; null and empty texts are documents of no tokens; null
keys are carried along; repeated rows are documents each; an empty table gives
an empty table; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe import codec_for, default_vocabulary, vocabulary_bytes
from .common import Stage, read_table, text_or_empty

BLOCK_TOKENS = 1 << 16
END_OF_DOCUMENT = 50_256  # free in the vocabulary
DTYPE = "<u2"


def write_token_files(docs: DataFrame, *, key: str = "doc_id", text: str = "text", block_tokens: int = BLOCK_TOKENS, eod: int = END_OF_DOCUMENT) -> DataFrame:
    """One flat file for each task, as rows (file, block, data), and rows (file, ids) that list its documents in order."""
    path, pattern = default_vocabulary()
    shipped = docs.sparkSession.sparkContext.broadcast(vocabulary_bytes(path))
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec = codec_for(shipped.value, pattern)
        file, block, waiting, held = TaskContext.get().partitionId(), 0, [], 0
        listings = 0
        for batch in batches:
            listings += 1  # listings are numbered downward from -1, beside the blocks
            yield pd.DataFrame({"file": [file], "block": [-listings], "data": [None], "ids": [batch["key"].tolist()]})
            for ids in codec.encode_texts(batch["text"].tolist()):
                waiting.append(np.append(ids, eod).astype(DTYPE))
                held += len(ids) + 1
                if held >= 16 * block_tokens:
                    tokens = np.concatenate(waiting)
                    cut = held // block_tokens * block_tokens
                    yield pd.DataFrame({"file": file, "block": range(block, block + cut // block_tokens), "data": [tokens[a : a + block_tokens].tobytes() for a in range(0, cut, block_tokens)], "ids": None})
                    block, waiting, held = block + cut // block_tokens, [tokens[cut:]], held - cut
        tokens = np.concatenate(waiting) if waiting else np.zeros(0, dtype=DTYPE)
        pieces = [tokens[a : a + block_tokens].tobytes() for a in range(0, len(tokens), block_tokens)]
        yield pd.DataFrame({"file": file, "block": range(block, block + len(pieces)), "data": pieces, "ids": None})
        codec.rest()

    return docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInPandas(run, f"file long, block long, data binary, ids array<{kind}>")


def read_flat_files(spark: SparkSession, path: str, *, block_tokens: int = BLOCK_TOKENS, dtype: str = DTYPE) -> DataFrame:
    """Flat files (each below Spark's 2 GB limit for one binary value) as rows (file, block, data)."""
    step = block_tokens * np.dtype(dtype).itemsize
    files = spark.read.format("binaryFile").load(path).select(F.col("path").alias("file"), F.col("content"))
    cuts = F.expr(f"transform(sequence(0L, (length(content) - 1) div {step}), b -> struct(b AS block, substring(content, cast(b * {step} + 1 AS int), {step}) AS data))")
    return files.filter(F.length("content") > 0).select("file", F.explode(cuts).alias("b")).select("file", "b.block", "b.data")


def scan_blocks(blocks: DataFrame, *, eod: int = END_OF_DOCUMENT, dtype: str = DTYPE) -> DataFrame:
    """file, block, size, ends (separators), head, tail and inner (lengths of the documents within) of each block."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for data in batch["data"]:
                tokens = np.frombuffer(data, dtype=dtype)
                at = np.flatnonzero(tokens == eod)
                n = len(tokens)
                rows.append((n, len(at), int(at[0]) if len(at) else n, n - 1 - int(at[-1]) if len(at) else n, np.diff(at) - 1))
            yield pd.DataFrame({"file": batch["file"].array, "block": batch["block"].array} | {c: [r[i] for r in rows] for i, c in enumerate(["size", "ends", "head", "tail", "inner"])})

    kind = blocks.schema["file"].dataType.simpleString()
    return blocks.select("file", "block", "data").mapInPandas(run, f"file {kind}, block long, size long, ends long, head long, tail long, inner array<long>")


def stitch(scanned: DataFrame) -> DataFrame:
    """file, ordinal, n_tokens and terminated of every document."""
    order = Window.partitionBy("file").orderBy("block")
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    slim = scanned.select("file", "block", "size", "ends", "head", "tail")
    carried = (
        slim.withColumn("base", F.coalesce(F.sum("ends").over(before), F.lit(0)))
        .withColumn("offset", F.coalesce(F.sum("size").over(before), F.lit(0)))
        .withColumn("open_at", F.when(F.col("ends") > 0, F.col("offset") + F.col("size") - F.col("tail")))
        .withColumn("open", F.col("offset") - F.coalesce(F.last("open_at", ignorenulls=True).over(before), F.lit(0)))
        .withColumn("is_last", F.lead("block").over(order).isNull())
        .select("file", "block", "ends", "head", "tail", "size", "base", "open", "is_last")
    )
    crossing = carried.filter("ends > 0").select("file", F.col("base").alias("ordinal"), (F.col("open") + F.col("head")).alias("n_tokens"), F.lit(True).alias("terminated"))
    rest = F.when(F.col("ends") > 0, F.col("tail")).otherwise(F.col("open") + F.col("size"))
    unfinished = carried.filter("is_last").select("file", (F.col("base") + F.col("ends")).alias("ordinal"), rest.alias("n_tokens"), F.lit(False).alias("terminated")).filter("n_tokens > 0")
    within = (
        scanned.filter(F.size("inner") > 0)
        .join(carried.select("file", "block", "base"), ["file", "block"])
        .select("file", "base", F.posexplode("inner").alias("pos", "n_tokens"))
        .select("file", (F.col("base") + 1 + F.col("pos")).alias("ordinal"), "n_tokens", F.lit(True).alias("terminated"))
    )
    return crossing.unionByName(unfinished).unionByName(within)


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode all documents to flat files, forget their borders, find them again and name the counts by the files' listings."""
    stage = Stage(spark, "tokens")
    files = stage.keep(write_token_files(read_table(spark, sf_dir, "documents").select("doc_id", "text")), "files")
    scanned = stage.keep(scan_blocks(files.filter("data IS NOT NULL")), "scanned")
    order = Window.partitionBy("file").orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    listed = (
        files.filter("ids IS NOT NULL")
        .select("file", "ids", "block", F.size("ids").alias("n"))
        .withColumn("base", F.coalesce(F.sum("n").over(order), F.lit(0)))
        .select("file", "base", F.posexplode("ids").alias("pos", "doc_id"))
        .select("file", (F.col("base") + F.col("pos")).alias("ordinal"), "doc_id")
    )
    return listed.join(stitch(scanned), ["file", "ordinal"]).select("doc_id", "n_tokens", "terminated", "file", "ordinal")
