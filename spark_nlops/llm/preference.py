"""Preference formatting of conversation pairs.

A pair holds a chosen and a rejected conversation.  Their longest common prefix of
turns is rendered once as the prompt; what follows is rendered for each side as a
completion, with the spans a trainer may learn from (assistant turns, their end
mark included).  The prompt is never learned from.

Both sides meet turn by turn, on (pair, turn), so that the comparison of long
conversations spreads; only then a pair's turns are gathered, which is the size of
one finished example.

Defined results: null roles count as ``unknown`` and null texts as empty; rows
without a conversation can't belong to a pair and are left out; a null turn comes
first; several different rows of one turn are one turn of several messages, by
role and text, and repeated rows count once; a pair with one conversation has an
empty prompt and one empty side; equal conversations are all prompt; very long
texts are rendered whole; an empty table gives an empty table; other columns are
not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table

OPEN, SHUT, END = "<|", "|>\n", "<|end|>\n"


def render(messages: Column) -> Column:
    return F.array_join(F.transform(messages, lambda m: F.concat(F.lit(OPEN), m["role"], F.lit(SHUT), m["text"], F.lit(END))), "")


def learnable_spans(messages: Column, role: str = "assistant") -> Column:
    """Character spans ``start-end`` of the role's texts within the rendered messages, joined by semicolons."""

    def step(state: Column, m: Column) -> Column:
        start = state["at"] + F.length(m["role"]) + F.lit(len(OPEN + SHUT))
        end = start + F.length(m["text"]) + F.lit(len(END))
        span = F.concat(start.cast("string"), F.lit("-"), end.cast("string"))
        return F.struct(
            end.cast("int").alias("at"),
            F.when(m["role"] == role, F.concat(state["spans"], F.array(span))).otherwise(state["spans"]).alias("spans"),
        )

    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("spans"))
    return F.array_join(F.aggregate(messages, start, step, lambda s: s["spans"]), ";")


def format_preferences(sides: DataFrame) -> DataFrame:
    """One example for each pair; sides has pair, chosen (boolean), turn, role and text."""
    message = F.struct(F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    turns = (
        sides.filter("pair IS NOT NULL")
        .groupBy("pair", "turn")
        .agg(
            F.sort_array(F.collect_set(F.when(F.col("chosen"), message))).alias("c"),
            F.sort_array(F.collect_set(F.when(~F.col("chosen"), message))).alias("r"),
        )
    )
    pairs = turns.groupBy("pair").agg(F.sort_array(F.collect_list(F.struct("turn", "c", "r"))).alias("turns"))
    parting = F.array_position(F.transform("turns", lambda t: t["c"] == t["r"]), False)
    shared = F.when(parting > 0, parting - 1).otherwise(F.size("turns")).cast("int")
    pairs = pairs.withColumn("n_prompt_turns", shared)
    rest = F.slice("turns", F.col("n_prompt_turns") + 1, F.size("turns"))
    messages = lambda turns, side: F.flatten(F.transform(turns, lambda t: t[side]))
    pairs = pairs.select(
        "pair",
        "n_prompt_turns",
        messages(F.slice("turns", F.lit(1), F.col("n_prompt_turns")), "c").alias("p"),
        messages(rest, "c").alias("c"),
        messages(rest, "r").alias("r"),
    )
    return pairs.select(
        F.col("pair").alias("pair_id"),
        "n_prompt_turns",
        render(F.col("p")).alias("prompt"),
        render(F.col("c")).alias("chosen"),
        learnable_spans(F.col("c")).alias("chosen_spans"),
        render(F.col("r")).alias("rejected"),
        learnable_spans(F.col("r")).alias("rejected_spans"),
    )


def neighbours_as_pairs(conversations: DataFrame) -> DataFrame:
    """Conversations 2k (chosen) and 2k + 1 (rejected) as pair k."""
    return conversations.filter("conv_id IS NOT NULL").select(
        F.shiftright(F.col("conv_id").cast("long"), 1).alias("pair"), (F.pmod("conv_id", F.lit(2)) == 0).alias("chosen"), "turn", "role", "text"
    )


def op8_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_preferences(neighbours_as_pairs(read_table(spark, sf_dir, "conversations")))


OP8_SQL = r"""
WITH side AS (
  SELECT DISTINCT conv_id // 2 AS pair, conv_id % 2 = 0 AS chosen, coalesce(turn, -1) AS turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text
  FROM conversations WHERE conv_id IS NOT NULL
), turns AS (
  SELECT pair, turn, list({r: role, t: text} ORDER BY role, text) FILTER (chosen) AS c, list({r: role, t: text} ORDER BY role, text) FILTER (NOT chosen) AS r
  FROM side GROUP BY pair, turn
), parting AS (
  SELECT pair, min(turn) FILTER (c IS DISTINCT FROM r) AS at, count(*) AS n FROM turns GROUP BY pair
), shared AS (
  SELECT p.pair, any_value(p.at) AS at, count(*) FILTER (p.at IS NULL OR t.turn < p.at) AS n_prompt_turns FROM parting p JOIN turns t USING (pair) GROUP BY p.pair
), said AS (
  SELECT s.*, s.turn < h.at OR h.at IS NULL AS in_prompt, '<|' || role || '|>' || chr(10) || text || '<|end|>' || chr(10) AS line
  FROM side s JOIN shared h USING (pair)
), placed AS (
  SELECT *, coalesce(sum(length(line)) OVER (PARTITION BY pair, chosen, in_prompt ORDER BY turn, role, text ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM said
), spanned AS (
  SELECT *, (before + length(role) + 5)::BIGINT || '-' || (before + length(line))::BIGINT AS span FROM placed
)
SELECT h.pair AS pair_id, h.n_prompt_turns::INTEGER AS n_prompt_turns,
  coalesce(string_agg(line, '' ORDER BY turn, role, text) FILTER (in_prompt AND chosen), '') AS prompt,
  coalesce(string_agg(line, '' ORDER BY turn, role, text) FILTER (NOT in_prompt AND chosen), '') AS chosen,
  coalesce(string_agg(span, ';' ORDER BY turn, role, text) FILTER (NOT in_prompt AND chosen AND role = 'assistant'), '') AS chosen_spans,
  coalesce(string_agg(line, '' ORDER BY turn, role, text) FILTER (NOT in_prompt AND NOT chosen), '') AS rejected,
  coalesce(string_agg(span, ';' ORDER BY turn, role, text) FILTER (NOT in_prompt AND NOT chosen AND role = 'assistant'), '') AS rejected_spans
FROM shared h JOIN spanned s USING (pair) GROUP BY h.pair, h.n_prompt_turns
"""
