"""Text preparation as column functions: words, markup removal, chunks, snippets, token estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}"
LICENSE = r"(?:Released|Licensed) under [A-Za-z0-9. -]*[A-Za-z0-9]"


def words(text: Column) -> Column:
    """Lower-cased runs of characters other than white space."""
    return F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")


def token_estimate(text: Column) -> Column:
    return F.size(words(F.coalesce(text, F.lit(""))))


def html_to_text(html: Column) -> Column:
    """Scripts, styles, comments and tags removed, common entities decoded, white space collapsed."""
    out = F.regexp_replace(html, r"(?is)<script.*?</script>", " ")
    out = F.regexp_replace(out, r"(?is)<style.*?</style>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for entity, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(sign))
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def squeeze(text: Column) -> Column:
    return F.trim(F.regexp_replace(text, r"\s+", " "))


def chunk(df: DataFrame, text: str, size: int, overlap: int, out: str = "chunk") -> DataFrame:
    """One row for each window of ``size`` words, the next one starting ``size - overlap`` words later; chunk_no counts from 0."""
    if not 0 <= overlap < size:
        raise ValueError("overlap must be from 0 to size - 1")
    step = size - overlap
    all_words = F.filter(F.split(F.col(text), r"\s+"), lambda w: w != "")
    cut = F.expr(f"transform(sequence(0, greatest(0, (size(_w) - {overlap} - 1) div {step})), i -> array_join(slice(_w, i * {step} + 1, {size}), ' '))")
    return df.withColumn("_w", all_words).select(*df.columns, F.posexplode(cut).alias("chunk_no", out))


def find_all(text: Column, pattern: str) -> Column:
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(0))


def placed_snippets(text: Column, found: Column) -> Column:
    """Found strings as (start, end, text), each searched behind the one before; strings that aren't in the text go."""
    def step(state: Column, s: Column) -> Column:
        at = F.locate_from(s, text, state["at"]) if hasattr(F, "locate_from") else F.call_function("locate", s, text, state["at"])
        item = F.struct((at - 1).cast("int").alias("start"), (at - 1 + F.length(s)).cast("int").alias("end"), s.alias("text"))
        return F.struct(
            F.when(at > 0, at + F.length(s)).otherwise(state["at"]).cast("int").alias("at"),
            F.when(at > 0, F.concat(state["out"], F.array(item))).otherwise(state["out"]).alias("out"),
        )

    start = F.struct(F.lit(1).alias("at"), F.array().cast("array<struct<start:int,end:int,text:string>>").alias("out"))
    return F.aggregate(found, start, step, lambda s: s["out"])
