"""The SQL surface: row-wise NL functions, a grouped one, and table functions."""

from __future__ import annotations

import re
from collections.abc import Callable

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .text import EMAIL, LICENSE

PATTERNS = {"email": EMAIL, "license": LICENSE}


def register_label(spark: SparkSession, name: str, answer: Callable[[list[str]], list[bool]]) -> None:
    """A boolean function of a prompt, for SQL; marked non-deterministic so that no call is made twice."""

    @F.pandas_udf("boolean")
    def label(prompts: pd.Series) -> pd.Series:
        given = prompts.notna()
        out = pd.Series([None] * len(prompts), dtype=object)
        if given.any():
            out[given] = [bool(x) for x in answer(prompts[given].tolist())]
        return out

    spark.udf.register(name, label.asNondeterministic())


def register_summary(spark: SparkSession, name: str = "nl_summary") -> None:
    """The sorted distinct words of a small group's texts: an order-free reducer for SQL's GROUP BY."""

    @F.pandas_udf("string")
    def summary(texts: pd.Series) -> str:
        return " ".join(sorted({w for t in texts.dropna() for w in t.lower().split()}))

    spark.udf.register(name, summary)


@F.udtf(returnType="start int, end int, text string")
class Snippets:
    """``nl_snippets(text, kind)``: one row for each e-mail address or licence line."""

    def eval(self, text: str, kind: str):
        for m in re.finditer(PATTERNS[kind], text or ""):
            yield m.start(), m.end(), m.group()


@F.udtf(returnType="label string, hits int")
class Labels:
    """``nl_labels(text, 'a,b,c')``: one row for each listed label word that the text has, with its count."""

    def eval(self, text: str, labels: str):
        words = re.findall(r"\w+", (text or "").lower())
        for label in labels.split(","):
            if n := words.count(label.strip().lower()):
                yield label.strip(), n


def register_snippets(spark: SparkSession, name: str = "nl_snippets", labels: str = "nl_labels") -> None:
    spark.udtf.register(name, Snippets)
    spark.udtf.register(labels, Labels)
