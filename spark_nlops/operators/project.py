"""Row-wise NL operators: projection to text, and extraction of verbatim snippets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import find_all, placed_snippets
from ..models.base import ModelBackend
from ..template import Template


def nl_project(df: DataFrame, template: str | Template, out: str, model: ModelBackend) -> DataFrame:
    """All columns and the model's text; null where a slot is null."""
    template = Template(template) if isinstance(template, str) else template
    return model.text(df, template.bind(df), out)


def nl_extract(df: DataFrame, template: str | Template, out: str, *, text: str, pattern: str | None = None, model: ModelBackend | None = None) -> DataFrame:
    """All columns and the snippets as (start, end, text); whatever isn't in the source at its place is left out.

    ``pattern`` is the rule form; a model names its snippets on lines of its text.
    """
    template = Template(template) if isinstance(template, str) else template
    template.bind(df)
    if pattern is not None:
        found, named = find_all(F.col(text), pattern), df
    else:
        named = model.text(df, template, "_said")
        found = F.filter(F.split("_said", "\n"), lambda s: s != "")
    placed = named.withColumn("_found", found)
    return placed.withColumn(out, placed_snippets(F.col(text), F.col("_found"))).drop("_found", "_said")
