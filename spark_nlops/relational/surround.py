"""Relational operators that programs need around NL operators, each as one query with its SQL twin.

These are built-in Catalyst operators; the catalogue shows that they compose with NL
results and pins their semantics against a second engine.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import read_rows, read_table, write_partitioned, write_rows
from ..staging import shared_folder, staged

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def rel(name: str, sql: str | None = None):
    def put(f):
        QUERIES[f"rel_{name}"] = f
        if sql is not None:
            SQL[f"rel_{name}"] = sql
        return f

    return put


def T(spark: SparkSession, sf: str, name: str, *columns: str) -> DataFrame:  # noqa: N802
    return read_table(spark, sf, name, list(columns) or None)


def money(c: str):
    return F.col(c).cast("decimal(18,2)")


def _scratch(spark: SparkSession, name: str) -> str:
    import uuid

    return f"{shared_folder(spark)}/nlops-{name}-{uuid.uuid4().hex[:10]}"


# --- scans ---------------------------------------------------------------------------
@rel("scan_prune", "SELECT doc_id, lang FROM documents WHERE n_chars > 1000 AND lang = 'fr'")
def _(s, d):
    return T(s, d, "documents").filter("n_chars > 1000 AND lang = 'fr'").select("doc_id", "lang")


_EVENTS = "SELECT event_id, user_id, event_type, value FROM events"


def _round_trip(s, d, form):
    df = T(s, d, "events", "event_id", "user_id", "event_type", "value")
    path = _scratch(s, form)
    write_rows(df, path, form)
    return read_rows(s, path, form, df.schema)


@rel("scan_json_roundtrip", _EVENTS)
def _(s, d):
    return _round_trip(s, d, "json")


@rel("scan_csv_roundtrip", _EVENTS)
def _(s, d):
    return _round_trip(s, d, "csv")


@rel("scan_orc_roundtrip", _EVENTS)
def _(s, d):
    return _round_trip(s, d, "orc")


@rel("scan_partitioned", "SELECT event_id, value, event_type FROM events WHERE event_type = 'view'")
def _(s, d):
    path = _scratch(s, "partitioned")
    write_partitioned(T(s, d, "events", "event_id", "value", "event_type"), path, ["event_type"])
    return s.read.parquet(path).filter("event_type = 'view'").select("event_id", "value", "event_type")


# --- projections and predicates --------------------------------------------------------
@rel("proj_expr", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS revenue, CASE WHEN l_quantity > 25 THEN 'bulk' WHEN l_quantity > 10 THEN 'some' ELSE 'few' END AS size FROM lineitem")
def _(s, d):
    size = F.when(F.col("l_quantity") > 25, "bulk").when(F.col("l_quantity") > 10, "some").otherwise("few")
    return T(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("revenue"), size.alias("size"))


@rel("pred_mix", "SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#1', 'Brand#2', 'Brand#11', 'Brand#12', 'Brand#13') AND p_name LIKE '%a%' AND regexp_matches(p_type, '[A-Z]') AND p_retailprice IS NOT NULL AND p_brand IS NOT DISTINCT FROM p_brand")
def _(s, d):
    c = F.col
    return T(s, d, "part").filter(c("p_size").between(5, 20) & c("p_brand").isin("Brand#1", "Brand#2", "Brand#11", "Brand#12", "Brand#13") & c("p_name").like("%a%") & c("p_type").rlike("[A-Z]") & c("p_retailprice").isNotNull() & c("p_brand").eqNullSafe(c("p_brand"))).select("p_partkey", "p_brand")


# --- joins ---------------------------------------------------------------------------
@rel("join_inner_hash", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey")
def _(s, d):
    return T(s, d, "orders").join(T(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@rel("join_broadcast", "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def _(s, d):
    return T(s, d, "nation").join(F.broadcast(T(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")  # five regions by definition


@rel("join_sort_merge", "SELECT o_orderkey, count(*) AS n_lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def _(s, d):
    return T(s, d, "orders", "o_orderkey").join(T(s, d, "lineitem", "l_orderkey").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n_lines"))


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    # the other side lists documents that may be missing here
    @rel(f"join_{_how}", f"SELECT d.doc_id AS doc_id, l.doc_id AS label_id, quality, toxic FROM (SELECT doc_id FROM documents WHERE n_chars > 500) d {_sql} JOIN labels l ON d.doc_id = l.doc_id")
    def _(s, d, how=_how):
        left = T(s, d, "documents", "doc_id", "n_chars").filter("n_chars > 500").select("doc_id")
        right = T(s, d, "labels").withColumnRenamed("doc_id", "label_id")
        return left.join(right, F.col("doc_id") == F.col("label_id"), how)


@rel("join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def _(s, d):
    return T(s, d, "documents", "doc_id").join(T(s, d, "labels").filter("quality = 1"), "doc_id", "left_semi")


@rel("join_anti", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def _(s, d):
    return T(s, d, "documents", "doc_id").join(T(s, d, "labels"), "doc_id", "left_anti")


@rel("join_cross_nl", "SELECT r_name, n_name FROM region CROSS JOIN nation WHERE length(n_name) > length(r_name)")
def _(s, d):
    return T(s, d, "region").crossJoin(T(s, d, "nation")).filter(F.length("n_name") > F.length("r_name")).select("r_name", "n_name")


@rel("join_range", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND b.p_size BETWEEN a.p_size - 1 AND a.p_size + 1")
def _(s, d):
    """Keys of one brand and size meet as arrays: blocks of 4096 keys pair up with those of the same and both neighbouring sizes, and only pairs that are listed become rows."""
    place = Window.partitionBy("brand", "size").orderBy("key")
    part = T(s, d, "part", "p_partkey", "p_brand", "p_size").filter("p_brand IS NOT NULL AND p_size IS NOT NULL AND p_partkey IS NOT NULL")
    dealt = part.select(F.col("p_partkey").alias("key"), F.col("p_brand").alias("brand"), F.col("p_size").alias("size")).withColumn("block", F.floor((F.row_number().over(place) - 1) / 4096))
    blocks = staged(dealt.groupBy("brand", "size", "block").agg(F.collect_list("key").alias("keys")), "blocks")
    left = blocks.select("brand", F.explode(F.array(F.col("size") - 1, F.col("size"), F.col("size") + 1)).alias("size"), F.col("keys").alias("lefts"))
    cells = left.join(blocks.select("brand", "size", F.col("keys").alias("rights")), ["brand", "size"]).filter(F.array_min("lefts") < F.array_max("rights"))
    cells = cells.select("lefts", "rights").repartition(8 * s.sparkContext.defaultParallelism)
    return cells.select(F.explode("lefts").alias("a"), "rights").select("a", F.explode("rights").alias("b")).filter("a < b")


@rel("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts BETWEEN a.ts - INTERVAL 10 MINUTE AND a.ts + INTERVAL 10 MINUTE")
def _(s, d):
    """Ten-minute buckets make the interval an equality; the left side is listed in three buckets."""
    e = T(s, d, "events", "event_id", "user_id", "ts").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    bucket = F.floor(F.col("at") / 600_000_000)
    left = e.select(F.col("event_id").alias("a"), "user_id", F.col("at").alias("x"), F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("slot"))
    right = e.select(F.col("event_id").alias("b"), "user_id", F.col("at").alias("y"), bucket.alias("slot"))
    return left.join(right, ["user_id", "slot"]).filter("a < b AND abs(x - y) <= 600000000").select("a", "b")


@rel("join_asof", "SELECT p.event_id AS event_id, max_by(v.event_id, (v.ts, v.event_id)) AS view_id FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id")
def _(s, d):
    """The latest view before each purchase by one window over both, without pairing rows."""
    e = T(s, d, "events", "event_id", "user_id", "event_type", "ts").filter("event_type IN ('view', 'purchase')")
    seen = F.when(F.col("event_type") == "view", F.col("event_id"))
    before = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", F.last(seen, ignorenulls=True).over(before)).filter("event_type = 'purchase'").select("event_id", "view_id")


# --- aggregates ------------------------------------------------------------------------
@rel("agg_basic", "SELECT l_returnflag, l_linestatus, sum(l_quantity::DECIMAL(18,2))::DOUBLE AS qty, count(*) AS n, round(avg(l_discount), 6) AS disc, min(l_extendedprice) AS low, max(l_extendedprice) AS high, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY ALL")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum(money("l_quantity")).cast("double").alias("qty"), F.count("*").alias("n"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@rel("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def _(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@rel("agg_approx_distinct", "SELECT event_type, true AS within FROM events GROUP BY event_type")
def _(s, d):
    """The sketch's count is within 10 % of the exact one."""
    near = F.abs(F.approx_count_distinct("user_id", 0.02) - F.count_distinct("user_id")) <= 0.1 * F.count_distinct("user_id")
    return T(s, d, "events").groupBy("event_type").agg(near.alias("within"))


@rel("agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS median, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")
def _(s, d):
    return T(s, d, "documents", "lang", "n_chars").groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("median"), F.percentile("n_chars", F.lit(0.9)).alias("p90"))


@rel("agg_sort", "SELECT source, max_by(doc_id, (n_chars, doc_id)) AS longest, min_by(doc_id, (n_chars, doc_id)) AS shortest, string_agg(lang, ',' ORDER BY lang) AS langs FROM (SELECT source, doc_id, n_chars, lang FROM documents) GROUP BY source")
def _(s, d):
    return T(s, d, "documents", "source", "doc_id", "n_chars", "lang").groupBy("source").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"), F.min_by("doc_id", F.struct("n_chars", "doc_id")).alias("shortest"), F.array_join(F.array_sort(F.collect_list("lang")), ",").alias("langs"))


@rel("agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def _(s, d):
    return T(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@rel("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(s, d):
    return T(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@rel("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping(o_orderstatus, o_orderpriority)::BIGINT AS level FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(s, d):
    T(s, d, "orders").createOrReplaceTempView("nlops_orders")
    return s.sql("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority) AS level FROM nlops_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@rel("agg_filter_clause", "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'purchase') AS buys FROM events GROUP BY user_id")
def _(s, d):
    T(s, d, "events").createOrReplaceTempView("nlops_events")
    return s.sql("SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) FILTER (WHERE event_type = 'purchase') AS buys FROM nlops_events GROUP BY user_id")


@rel("agg_pivot", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click FROM events GROUP BY user_id")
def _(s, d):
    return T(s, d, "events").groupBy("user_id").pivot("event_type", ["view", "click"]).agg(F.count("event_id")).select("user_id", F.coalesce("view", F.lit(0)).alias("view"), F.coalesce("click", F.lit(0)).alias("click"))


JUNK_SQL = "(length(text) - length(regexp_replace(text, '[#$%&*!]', '', 'g'))) > 0.05 * length(text) OR (length(text) - length(regexp_replace(text, '[A-Z]', '', 'g'))) > 0.4 * length(text)"


@rel("agg_over_nl", f"SELECT lang, count(*) AS n FROM documents WHERE {JUNK_SQL} GROUP BY lang")
def _(s, d):
    from ..operators.filter import nl_filter
    from ..workloads.common import JUNK, junk_oracle

    return nl_filter(T(s, d, "documents"), JUNK, junk_oracle(), plan="reference").df.groupBy("lang").agg(F.count("*").alias("n"))


# --- windows ---------------------------------------------------------------------------
@rel("win_rank", "SELECT p_partkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 9) AS pr, round(cume_dist() OVER v, 9) AS cd, ntile(4) OVER w AS nt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)")
def _(s, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    b = lambda c: c.cast("bigint")
    return T(s, d, "part").select("p_partkey", b(F.row_number().over(w)).alias("rn"), b(F.rank().over(v)).alias("rk"), b(F.dense_rank().over(v)).alias("dr"), F.round(F.percent_rank().over(v), 9).alias("pr"), F.round(F.cume_dist().over(v), 9).alias("cd"), b(F.ntile(4).over(w)).alias("nt"))


@rel("win_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS later, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return T(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("later"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(whole).alias("second"))


@rel("win_rows_frame", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS last_three FROM events")
def _(s, d):
    return T(s, d, "events").select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("last_three"))


@rel("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS past_day FROM events")
def _(s, d):
    at = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)
    return T(s, d, "events").withColumn("at", at).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400, 0)).alias("past_day"))


# --- order, limits, sets -----------------------------------------------------------------
@rel("sort_multi", "SELECT o_orderkey, o_orderpriority, o_totalprice FROM orders ORDER BY o_orderpriority DESC NULLS LAST, o_totalprice, o_orderkey")
def _(s, d):
    return T(s, d, "orders").select("o_orderkey", "o_orderpriority", "o_totalprice").orderBy(F.desc_nulls_last("o_orderpriority"), "o_totalprice", "o_orderkey")


@rel("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50 OFFSET 25")
def _(s, d):
    return T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(25).limit(50).select("o_orderkey")


@rel("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(s, d):
    return T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


@rel("topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return T(s, d, "orders").withColumn("rn", F.row_number().over(w)).filter("rn <= 3").select("o_custkey", "o_orderkey")


_A, _B = "SELECT source, lang FROM documents WHERE n_chars > 2000", "SELECT source, lang FROM documents WHERE n_chars < 3000"
for _name, _sql, _op in (
    ("union", "UNION", lambda a, b: a.union(b).distinct()), ("union_all", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)), ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    @rel(f"set_{_name}", f"{_A} {_sql} {_B}")
    def _(s, d, op=_op):
        docs = T(s, d, "documents", "source", "lang", "n_chars")
        return op(docs.filter("n_chars > 2000").select("source", "lang"), docs.filter("n_chars < 3000").select("source", "lang"))


@rel("set_distinct", "SELECT DISTINCT source, lang FROM documents")
def _(s, d):
    return T(s, d, "documents", "source", "lang").distinct()


# --- subqueries ------------------------------------------------------------------------
def _sql_query(name, text, tables):
    @rel(name, text)
    def _(s, d):
        for t in tables:
            T(s, d, t).createOrReplaceTempView(t)
        return s.sql(text)


_sql_query("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT max(o_totalprice) * 0.9 FROM orders)", ["orders"])
_sql_query("sub_exists", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.toxic = 1)", ["documents", "labels"])
_sql_query("sub_in", "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 9000)", ["orders", "customer"])
_sql_query("sub_correlated", "SELECT doc_id FROM documents d WHERE n_chars = (SELECT max(n_chars) FROM documents e WHERE e.source = d.source)", ["documents"])


# --- functions -------------------------------------------------------------------------
@rel("fn_string", r"SELECT doc_id, lower(trim(substr(text, 1, 20))) AS head, instr(text, 'the') AS at, len(string_split(text, ' ')) AS pieces, replace(substr(text, 1, 12), 'e', '3') AS leet, regexp_extract(text, '([A-Za-z]+)', 1) AS word, regexp_replace(substr(text, 1, 30), '[aeiou]', '_', 'g') AS masked, md5(text) AS h, length(text) AS n, concat_ws('-', source, lang) AS tag, levenshtein(source, lang) AS apart FROM documents")
def _(s, d):
    t = F.col("text")
    return T(s, d, "documents").select("doc_id", F.lower(F.trim(F.substring(t, 1, 20))).alias("head"), F.instr(t, "the").cast("bigint").alias("at"), F.size(F.split(t, " ", -1)).cast("bigint").alias("pieces"), F.replace(F.substring(t, 1, 12), F.lit("e"), F.lit("3")).alias("leet"), F.regexp_extract(t, "([A-Za-z]+)", 1).alias("word"), F.regexp_replace(F.substring(t, 1, 30), "[aeiou]", "_").alias("masked"), F.md5(t).alias("h"), F.length(t).cast("bigint").alias("n"), F.concat_ws("-", "source", "lang").alias("tag"), F.levenshtein("source", "lang").cast("bigint").alias("apart"))


@rel("fn_date", "SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, strftime(o_orderdate + INTERVAL 30 DAY, '%Y-%m-%d') AS due, extract(year FROM o_orderdate) AS y, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days FROM orders")
def _(s, d):
    o = F.col("o_orderdate")
    return T(s, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("month"), F.date_format(F.date_add(o, 30), "yyyy-MM-dd").alias("due"), F.year(o).cast("bigint").alias("y"), F.datediff(o, F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"))


@rel("fn_math", "SELECT l_orderkey, l_linenumber, floor(l_extendedprice)::BIGINT AS f, round(sqrt(l_quantity), 6) AS r, round(log2(l_quantity), 6) AS lg, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l, round(abs(l_discount - l_tax), 6) AS a, pow(l_quantity, 2) AS p FROM lineitem")
def _(s, d):
    return T(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.floor("l_extendedprice").alias("f"), F.round(F.sqrt("l_quantity"), 6).alias("r"), F.round(F.log2("l_quantity"), 6).alias("lg"), F.greatest("l_discount", "l_tax").alias("g"), F.least("l_discount", "l_tax").alias("l"), F.round(F.abs(F.col("l_discount") - F.col("l_tax")), 6).alias("a"), F.pow("l_quantity", F.lit(2)).alias("p"))


@rel("fn_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive, round(list_max(embedding)::DOUBLE, 6) AS high, round(embedding[1]::DOUBLE, 6) AS first, round(list_max(embedding[1:8])::DOUBLE, 6) AS high8, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS any_big FROM embeddings")
def _(s, d):
    e = F.col("embedding")
    return T(s, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("positive"), F.round(F.array_max(e).cast("double"), 6).alias("high"), F.round(e[0].cast("double"), 6).alias("first"), F.round(F.array_max(F.slice(e, 1, 8)).cast("double"), 6).alias("high8"), F.exists(e, lambda x: x > 0.3).alias("any_big"))


@rel("fn_array_explode", "SELECT vec_id, (i - 1)::BIGINT AS place, round(x::DOUBLE, 6) AS x FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS i FROM embeddings)")
def _(s, d):
    return T(s, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("p", "v")).select("vec_id", F.col("p").cast("bigint").alias("place"), F.round(F.col("v").cast("double"), 6).alias("x"))


@rel("fn_map", "SELECT user_id, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS shown, max(n) FILTER (event_type = 'view') AS views FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) GROUP BY user_id")
def _(s, d):
    counts = T(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    shown = F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.element_at("m", k))), ",")
    return counts.select("user_id", shown.alias("shown"), F.element_at("m", "view").alias("views"))


@rel("fn_json", "SELECT event_id, json_extract_string(props, '$.' || json_keys(props)[1]) AS first, json_keys(props)[1] AS name FROM events")
def _(s, d):
    keys = F.json_object_keys("props")
    named = T(s, d, "events").withColumn("name", keys[0]).withColumn("m", F.from_json("props", "map<string,string>"))
    return named.select("event_id", F.element_at("m", F.col("name")).alias("first"), "name")


@rel("fn_decimal", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18,2))::DOUBLE AS total FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(money("l_extendedprice")).cast("double").alias("total"))


# --- vectors ---------------------------------------------------------------------------
_PAIR = "FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1"


def _neighbours(s, d):
    e = T(s, d, "embeddings", "vec_id", "embedding")
    return e.select("vec_id", F.col("embedding").alias("x")).join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("y")), "vec_id")


for _name, _sql in (("dot", "list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"), ("cosine", "list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[])"), ("l2", "list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[])")):
    @rel(f"vec_{_name}", f"SELECT a.vec_id, round({_sql}, 6) AS v {_PAIR}")
    def _(s, d, name=_name):
        from ..vectors import similarity

        f = getattr(similarity, name)
        return _neighbours(s, d).select("vec_id", F.round(f(F.col("x"), F.col("y")), 6).alias("v"))


@rel("vec_norm", "SELECT vec_id, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS v FROM embeddings")
def _(s, d):
    from ..vectors.similarity import norm

    return T(s, d, "embeddings").select("vec_id", F.round(norm(F.col("embedding")), 6).alias("v"))


@rel("vec_mean", "SELECT label, i::BIGINT AS place, round(avg(x), 6) AS v FROM (SELECT label, unnest(embedding::DOUBLE[]) AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY ALL")
def _(s, d):
    return T(s, d, "embeddings").select("label", F.posexplode("embedding").alias("p", "x")).groupBy("label", F.col("p").cast("bigint").alias("place")).agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("v"))
