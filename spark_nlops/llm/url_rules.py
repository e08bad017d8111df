"""URL rules as a sort-merge range join, in DataFrame functions only.

A host is written with its labels reversed and each label closed by a dot
(``www.example.com`` -> ``com.example.www.``), so a rule for a host and its
subdomains is one interval of the sorted keys.  Rule intervals nest; every
interval border carries the stack of rules that are active from there on.  Pages
and borders are sorted together and each page takes over the last border's
stack; the rules' paths are then matched within that stack.

Pages are dealt to the sweeps in turn, never by host, so that a host with a third
of all rows spreads evenly.  The borders (at most two per rule) are repeated for
each sweep; the number of sweeps follows the rows, and a sweep has at least
``ROWS_A_BORDER`` rows for each border, so the copies of the borders stay a
fraction of the rows for rule tables of any length.

Defined results: null urls and urls without ``://`` have empty host and path and
the default verdict; empty tables give empty tables; repeated rows are judged
each; ties between equally long rules go to ``block``, then to the larger rule
text; other columns of the input, whatever their names, are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import read_table, shuffle_width

#: Rows of a sweep where the borders don't ask for more: what one task sorts with ease.
SWEEP_ROWS = 1 << 20
ROWS_A_BORDER = 8
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
RULE_TYPE = "array<struct<size:int,block:int,rule:string,path:string,verdict:string>>"


def _rest(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise(F.lit(""))


def url_host(url: Column) -> Column:
    host = F.regexp_extract(_rest(url), r"^[^/?#]*", 0)
    return F.coalesce(F.translate(host, UPPER, LOWER), F.lit(""))


def url_path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def host_key(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit("."))


def rule_frame(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Rules given as (host, path, verdict)."""
    return spark.createDataFrame(rules, "host string, path string, verdict string")


def interval_borders(rules: DataFrame) -> DataFrame:
    """One row per border key with the stack of rules active from it on (outermost first)."""
    rules = rules.select(
        host_key(F.col("host")).alias("prefix"),
        F.struct(
            (F.length("host") + F.length("path")).cast("int").alias("size"),
            (F.col("verdict") == "block").cast("int").alias("block"),
            F.concat("host", "path").alias("rule"),
            F.col("path"),
            F.col("verdict"),
        ).alias("item"),
    )
    stacks = rules.groupBy("prefix").agg(F.sort_array(F.collect_set("item")).alias("items"))
    # all label prefixes of a border: those whose rules can be active there
    labels = F.split(F.expr("substring(prefix, 1, length(prefix) - 1)"), r"\.", -1)
    opened = stacks.select(F.col("prefix").alias("border"), labels.alias("labels"), F.size(labels).alias("depth"))
    closed = stacks.select(
        F.concat(F.expr("substring(prefix, 1, length(prefix) - 1)"), F.lit("/")).alias("border"),
        labels.alias("labels"),
        (F.size(labels) - 1).alias("depth"),
    )
    # at a closing border only the enclosing prefixes remain; depth 0 leaves an empty stack
    borders = opened.unionByName(closed).select(
        "border",
        F.explode_outer(
            F.expr(
                "CASE WHEN depth > 0 THEN transform(sequence(1, depth), n -> concat(array_join(slice(labels, 1, n), '.'), '.')) END"
            )
        ).alias("prefix"),
    )
    active = borders.join(stacks, "prefix", "left")
    return active.groupBy("border").agg(
        F.sort_array(F.flatten(F.collect_list(F.coalesce("items", F.from_json(F.lit("[]"), RULE_TYPE))))).alias("stack")
    )


def sweep_count(n_pages: int, n_rules: int, width: int) -> int:
    """Sweeps for so many pages: the session's width while they are small, beyond that as many as keep them near ``SWEEP_ROWS``, fewer where borders would outweigh pages."""
    rows = max(2 * n_rules * ROWS_A_BORDER, min(SWEEP_ROWS, -(-n_pages // width)), 1)
    return max(1, -(-n_pages // rows))


def judge_urls(pages: DataFrame, rules: DataFrame, *, key: str = "page_id", url: str = "url", default: str = "allow") -> DataFrame:
    """page key, host, path, the longest fitting rule (or null) and the verdict."""
    spark = pages.sparkSession
    width = shuffle_width(spark)
    sweeps = sweep_count(pages.count(), rules.count(), width)
    rows = pages.select(
        F.col(key).alias("page_key"),
        url_host(F.col(url)).alias("host"),
        url_path(F.col(url)).alias("path"),
        F.pmod(F.monotonically_increasing_id(), F.lit(sweeps)).cast("int").alias("sweep"),
    ).select("*", host_key(F.col("host")).alias("at"), F.lit(1).alias("kind"), F.lit(None).cast(RULE_TYPE).alias("stack"))
    marks = interval_borders(rules).select(
        F.lit(None).cast(pages.schema[key].dataType).alias("page_key"),
        F.lit("").alias("host"),
        F.lit("").alias("path"),
        F.explode(F.sequence(F.lit(0), F.lit(sweeps - 1))).alias("sweep"),
        F.col("border").alias("at"),
        F.lit(0).alias("kind"),
        F.col("stack").cast(RULE_TYPE).alias("stack"),
    )
    sweep = Window.partitionBy("sweep").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    dealt = rows.unionByName(marks)
    if sweeps > width:  # more tasks than the session's shuffles have, each with about one sweep
        dealt = dealt.repartition(sweeps, "sweep")
    swept = dealt.withColumn("active", F.last("stack", ignorenulls=True).over(sweep)).filter("kind = 1")
    fits = F.filter("active", lambda r: F.col("path").startswith(r["path"]))
    return swept.withColumn("best", F.array_max(fits)).select(
        F.col("page_key").alias(key), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict")
    )


RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]


def op9_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(read_table(spark, sf_dir, "pages").select("page_id", "url"), rule_frame(spark, RULES))


OP9_SQL = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, coalesce(translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path
  FROM cut
), rules(rhost, rpath, verdict) AS (
  VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')
), fit AS (
  SELECT page_id, rhost || rpath AS rule, verdict,
         row_number() OVER (PARTITION BY page_id ORDER BY length(rhost || rpath) DESC, verdict DESC, rhost || rpath DESC) AS n
  FROM parts JOIN rules ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath)
)
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, 'allow') AS verdict
FROM parts p LEFT JOIN fit f ON f.page_id = p.page_id AND f.n = 1
"""
