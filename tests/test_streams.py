"""Streams: late rows, frozen filters, drift, stream-static similarity and state."""

import datetime as dt

from pyspark.sql import functions as F

from spark_nlops.models.rules import RuleModel
from spark_nlops.streaming import streams
from spark_nlops.vectors.embed import HashedNgrams
from spark_nlops.vectors.index import build_text_index, load_text_index


def at(minute):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minute)


def test_late_rows_are_dropped(spark, tmp_path):
    """The third file brings one row behind the watermark and one within it; the watermark holds one batch after it was reached."""
    schema = "event_id long, ts timestamp_ntz, value double"
    landing = str(tmp_path / "in")
    for n, rows in enumerate([[(1, at(0), 1.0), (2, at(300), 1.0)], [(6, at(310), 1.0)], [(3, at(10), 5.0), (4, at(290), 1.0)], [(5, at(900), 1.0)]]):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(landing)
        import time

        time.sleep(1.1)  # files are taken in order of their times
    counts = streams.window_counts(streams.read_events(spark, landing, files_per_batch=1), "tumbling")
    got = {r.start: (r.n, r.total) for r in streams.run_to_parquet(counts, str(tmp_path / "out"), str(tmp_path / "state")).collect()}
    assert got[at(0)] == (1, 1.0) and got[at(240)] == (1, 1.0) and got[at(300)] == (2, 2.0)


def test_frozen_filter_and_drift(spark, tmp_path):
    df = spark.createDataFrame([(i, at(i), float(i)) for i in range(100)], "event_id long, ts timestamp_ntz, value double")
    proxy, oracle = RuleModel(score="value / 100"), RuleModel(predicate="value % 2 = 0")
    stream = streams.read_events(spark, streams.land(df, 3))
    out = streams.run_to_parquet(streams.frozen_filter(stream, "{value} counts", proxy, oracle, 0.5, 0.8), str(tmp_path / "out"), str(tmp_path / "state"))
    assert sorted(r.value for r in out.collect()) == [float(x) for x in [*range(50, 80, 2), *range(80, 100)]]
    assert streams.drift(df, "{value} counts", proxy, RuleModel(predicate="value >= 60"), 0.5, "event_id", 1.0) == 1.0
    assert streams.drift(df, "{value} counts", proxy, RuleModel(predicate="value >= 0"), 0.5, "event_id", 1.0) == 0.5
    assert streams.drift(df, "{value} counts", proxy, RuleModel(predicate="false"), 0.5, "event_id", 1.0) == 1.0


def test_stream_meets_a_stored_index(spark, sf001, tmp_path):
    docs = spark.read.parquet(f"{sf001}/documents.parquet").select("doc_id", "text")
    build_text_index(docs, "doc_id", "text", HashedNgrams(), str(tmp_path / "index"))
    index = load_text_index(spark, str(tmp_path / "index"))
    landing = streams.land(docs.filter("doc_id < 20"))
    stream = spark.readStream.schema(docs.schema).parquet(landing)
    met = streams.similar_to_index(stream, "text", HashedNgrams(), index, 0.999).select("doc_id", "near_key")
    got = {(r.doc_id, r.near_key) for r in streams.run_to_parquet(met, str(tmp_path / "out"), str(tmp_path / "state")).collect()}
    assert {(i, i) for i in range(20)} <= got


def test_duplicates_within_watermark(spark, tmp_path):
    df = spark.createDataFrame([(i % 5, at(i), 1.0) for i in range(50)], "event_id long, ts timestamp_ntz, value double")
    kept = streams.first_of_each(streams.read_events(spark, streams.land(df)), ["event_id"], late="2 days")
    assert streams.run_to_parquet(kept, str(tmp_path / "out"), str(tmp_path / "state")).select(F.count_distinct("event_id"), F.count("*")).first() == (5, 5)


def test_stage_tables_can_be_cleared(spark):
    from spark_nlops import staging

    df = staging.staged(spark.range(5).toDF("x"))
    assert df.count() == 5 and staging._made
    staging.clear(spark)
    assert not staging._made
