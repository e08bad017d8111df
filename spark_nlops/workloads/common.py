"""Shared parts of the experiment workloads: templates, rule oracles and proxies over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..models.rules import RuleModel
from ..staging import staged
from ..vectors.containment import containment_candidates

JUNK = "{text} is junk"
TOXIC = "{text} is toxic"
CONTAINS = "{text:left} contains the passage {text:right}"
#: Words of the built-in insult rule (fixed values).
INSULTS = ("clown", "idiot", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless")

_SIGNS = "(length(text) - length(regexp_replace(text, '[#$%&*!]', '')))"
_CAPS = "(length(text) - length(regexp_replace(text, '[A-Z]', '')))"
_LENGTH = "greatest(length(text), 1)"

STRONG = f"({_SIGNS} + {_CAPS} / 4.0D) / cast({_LENGTH} as double)"
WEAK = f"{_CAPS} / cast({_LENGTH} as double)"


def junk_oracle() -> RuleModel:
    return RuleModel(predicate=f"{_SIGNS} > 0.05 * length(text) OR {_CAPS} > 0.4 * length(text)", model_id="junk-rule")


def junk_proxy(expr: str = STRONG) -> RuleModel:
    return RuleModel(score=f"least(1.0D, {expr})", predicate=f"({expr}) > 0.05", model_id="junk-score")


def toxic_oracle() -> RuleModel:
    return RuleModel(predicate=f"lower(text) RLIKE '(^|[^a-z])({'|'.join(INSULTS)})($|[^a-z])'", model_id="insult-rule")


def contains_oracle() -> RuleModel:
    return RuleModel(predicate="contains(left_text, right_text)", model_id="containment", holds=("left_text", "right_text"))


def contained_pairs(docs: DataFrame, items: DataFrame) -> DataFrame:
    """The truth: doc_id, item_id of verbatim containment."""
    right = items.select(F.col("item_id").alias("rk"), F.col("text").alias("passage"))
    met = staged(containment_candidates(docs, items, "doc_id", "text", "item_id", "text"), "met")
    return met.join(docs.select(F.col("doc_id").alias("lk"), "text"), "lk").join(right, "rk").select(F.col("lk").alias("doc_id"), F.col("rk").alias("item_id"), "text", "passage").filter(F.expr("contains(text, passage)")).select("doc_id", "item_id")
