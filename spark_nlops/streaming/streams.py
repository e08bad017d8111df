"""Structured Streaming: windows, late data, duplicates, frozen filters and per-user state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..models.base import ModelBackend
from ..operators.filter import route
from ..staging import shared_folder
from ..template import Template


def land(df: DataFrame, files: int | None = None) -> str:
    """Write a table as files of a landing folder, which a file stream can follow."""
    path = f"{shared_folder(df.sparkSession)}/nlops-landing-{uuid.uuid4().hex[:10]}"
    (df.repartition(files) if files else df).write.parquet(path)
    return path


def read_events(spark: SparkSession, folder: str, files_per_batch: int = 10_000) -> DataFrame:
    """A landing folder of events as a file stream; times become UTC instants, as watermarks need."""
    schema = spark.read.parquet(folder).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def window_counts(stream: DataFrame, kind: str, *, late: str = "1 hour", width: str = "1 hour", slide: str | None = None, gap: str = "30 minutes", by: list[str] | None = None) -> DataFrame:
    """Counts and sums by tumbling, sliding or session window; rows behind the watermark are dropped."""
    span = {"tumbling": lambda: F.window("ts", width), "sliding": lambda: F.window("ts", width, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    marked = stream.withWatermark("ts", late)
    name = "session_window" if kind == "session" else "window"
    counts = marked.groupBy(span, *(by or [])).agg(F.count("*").alias("n"), F.round(F.sum("value"), 6).alias("total"))
    return counts.select(F.col(f"{name}.start").alias("start"), F.col(f"{name}.end").alias("end"), *(by or []), "n", "total")


def first_of_each(stream: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def frozen_filter(stream: DataFrame, template: str, proxy: ModelBackend, oracle: ModelBackend, lo: float, hi: float) -> DataFrame:
    """A cascade with cuts learned on a batch: three routes by the proxy's raw score, the oracle in the middle."""
    t = Template(template)
    columns = stream.columns
    scored = proxy.score(stream, t, "_score").withColumn("_route", route(F.col("_score"), lo, hi))
    asked = oracle.label(scored, t, "_label")
    return asked.filter((F.col("_route") == "accept") | ((F.col("_route") == "ask") & F.col("_label"))).select(*columns)


def drift(batch: DataFrame, template: str, proxy: ModelBackend, oracle: ModelBackend, lo: float, key: str, rate: float, seed: int = 0) -> float:
    """Estimated recall of the lower cut on a fresh sample of a batch; 1 if the sample has no positive."""
    from ..stats.hashing import uniform

    t = Template(template)
    drawn = oracle.label(proxy.score(batch.filter(uniform(F.col(key), seed) < rate), t, "_score"), t, "_label")
    kept, due = drawn.agg(F.sum(((F.col("_score") >= lo) & F.col("_label")).cast("int")), F.sum(F.col("_label").cast("int"))).first()
    return 1.0 if not due else (kept or 0) / due


def similar_to_index(stream: DataFrame, text: str, embedder, index, least: float, out: str = "near_key") -> DataFrame:
    """Stream-static join: each row with the stored rows of its own bucket that are similar enough."""
    from ..vectors.index import hyperplane_bucket
    from ..vectors.similarity import cosine

    m = index.manifest
    own = embedder.embed(stream.withColumn("_t", F.coalesce(text, F.lit(""))), "_t", "_v").withColumn("_b", hyperplane_bucket(F.col("_v"), m["dim"], m["planes"]))
    stored = index.vectors.select(F.col("key").alias(out), F.col("vec").alias("_w"), F.col("bucket").alias("_c"))
    met = own.join(stored, F.col("_b") == F.col("_c"))
    return met.withColumn("sim", F.round(cosine(F.col("_v"), F.col("_w")), 9)).filter(F.col("sim") >= least).drop("_t", "_v", "_w", "_b", "_c")


class TopValues(StatefulProcessor):
    """Each user's k largest values so far."""

    k = 3

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getValueState("best", "values array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        held = list(self.best.get()[0]) if self.best.exists() else []
        for batch in rows:
            held += batch["value"].dropna().tolist()
        held = sorted(held, reverse=True)[: self.k]
        self.best.update((held,))
        yield pd.DataFrame({"user_id": [key[0]], "best": [held]})

    def close(self) -> None:
        pass


def running_top(stream: DataFrame) -> DataFrame:
    return stream.groupBy("user_id").transformWithStateInPandas(TopValues(), outputStructType="user_id bigint, best array<double>", outputMode="Update", timeMode="None")


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Process what is there and give the sink's rows; for bounded replays and tests."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def run_to_parquet(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """The same through a file sink, exactly once, on any file system."""
    query = stream.writeStream.format("parquet").outputMode("append").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)
