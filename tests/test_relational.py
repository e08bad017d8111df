import pytest

from spark_nlops.catalog import oracle_sql, queries


def test_range_join_meets_by_brand_and_size(spark, tmp_path):
    rows = [(i, f"b{i % 2}", (i // 2) % 3 * 2 + i % 5 // 4) for i in range(400)] + [(1000 + i, "full", 7) for i in range(4100)] + [(9000, "full", None), (9001, None, 7), (9002, "full", 8)]
    spark.createDataFrame(rows, "p_partkey long, p_brand string, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    got = queries()["rel_join_range"](spark, str(tmp_path))
    spark.read.parquet(f"{tmp_path}/part.parquet").createOrReplaceTempView("part")
    want = spark.sql(oracle_sql()["rel_join_range"])
    assert got.count() == want.count() > 4100 * 4099 / 2
    assert got.filter("a < 1000 OR b > 6000").exceptAll(want).count() == 0
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert any("Join" in x and "size" in x for x in plan.splitlines())  # candidates of a brand alone grow with the square of the table


def test_success_rate_reads_documents(spark, sf001):
    duckdb = pytest.importorskip("duckdb")
    duckdb.sql(f"CREATE OR REPLACE VIEW documents AS SELECT * FROM '{sf001}/documents.parquet'")
    got = queries()["m_success_rate"](spark, sf001)
    assert "FileScan parquet" in got._jdf.queryExecution().executedPlan().toString() or got.inputFiles()
    rate, n = got.first()
    assert (round(rate, 12), n) == (lambda r: (round(r[0], 12), r[1]))(duckdb.sql(oracle_sql()["m_success_rate"]).fetchall()[0])
    assert "m_lines_of_code" not in queries()
