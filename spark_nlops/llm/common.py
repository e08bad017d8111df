"""Helpers shared by the training-data operators: shared staging, splits, text access."""

from __future__ import annotations

import gc
import time
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..staging import shared_folder


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows of whole texts that travel between Spark and a Python worker together.
TEXT_ROWS = 1024


def small_batches(spark: SparkSession) -> None:
    """From now on the session's Arrow batches have at most ``TEXT_ROWS`` rows.

    Texts are wide rows, and a batch is held several times (as rows, in Spark's Arrow
    buffers, in the worker): the default of 10 000 rows makes that hundreds of MB for
    each executor.  A runtime setting, which changes no result; smaller ones stay.
    """
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name, "10000"))
    if now <= 0 or now > TEXT_ROWS:
        spark.conf.set(name, str(TEXT_ROWS))


def free_name(df: DataFrame, name: str) -> str:
    """The name, with underscores behind it until the table has no such column."""
    taken = set(map(str.lower, df.columns))
    while name.lower() in taken:
        name += "_"
    return name


class Stage:
    """Parquet tables in the shared folder that cut lineage between the jobs of one operator."""

    def __init__(self, spark: SparkSession, label: str) -> None:
        self.spark = spark
        self.base = f"{shared_folder(spark)}/nlops-{label}-{uuid.uuid4().hex[:12]}"

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.base}/{name}"
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def release(self) -> None:
        """Let Spark's context cleaner delete the shuffle files of finished jobs before the next ones write theirs."""
        gc.collect()
        self.spark._jvm.System.gc()
        time.sleep(1.0)  # the cleaner works beside us

    def clear(self) -> None:
        """Free all of them."""
        self.drop("")

    def drop(self, name: str) -> None:
        """Free an intermediate that no later plan reads."""
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.base}/{name}".rstrip("/"))
        path.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def crc_remainder(key: str, modulus: int) -> Column:
    """crc32 of the key's text, modulo; null keys give null."""
    return F.crc32(F.col(key).cast("string").cast("binary")) % F.lit(modulus)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def slices(lengths, budget: int):
    """Index ranges whose summed lengths stay near a budget, so that a batch's working set is bounded."""
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if i > start and total + n > budget:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(lengths):
        yield start, len(lengths)


def trim_memory() -> None:
    """At a task's end: give freed memory back, since Python workers go on with other stages."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass
