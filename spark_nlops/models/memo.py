"""Prompts are asked once: duplicates share an answer, and answers are kept in a table between runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..staging import staged
from ..template import Template
from .base import ModelBackend, pair_name


class PromptMemo(ModelBackend):
    """Wraps a model's ``label``: distinct prompts only, through the table at ``path`` if given.

    The table is append-only: (model_id, prompt_hash, answer).  Copies of a prompt are
    joined back by the 256-bit hash of the prompt.
    """

    def __init__(self, base: ModelBackend, path: str | None = None) -> None:
        self.base, self.path, self.model_id = base, path, base.model_id
        self.asked = 0

    def _known(self, df: DataFrame) -> DataFrame | None:
        if self.path is None:
            return None
        try:
            return df.sparkSession.read.parquet(self.path).filter(F.col("model_id") == self.model_id).select("prompt_hash", "answer")
        except Exception as e:  # the table isn't there yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return None

    def label(self, df, template: Template, out="label"):
        pair = any(s.side for s in template.slots)
        marked = df.withColumn("prompt_hash", F.sha2(template.prompt(df, pair_name) if pair else template.prompt(df), 256))
        distinct = marked.filter("prompt_hash IS NOT NULL").dropDuplicates(["prompt_hash"])
        known = self._known(df)
        todo = distinct if known is None else distinct.join(known, "prompt_hash", "left_anti")
        fresh = staged(self.base.label(todo, template, "answer").select("prompt_hash", "answer"), "memo")
        self.asked = fresh.count()
        if self.path is not None:
            fresh.select(F.lit(self.model_id).alias("model_id"), "prompt_hash", "answer").write.mode("append").parquet(self.path)
        answers = fresh if known is None else fresh.unionByName(known)
        return marked.join(answers, "prompt_hash", "left").withColumn(out, F.col("answer")).drop("prompt_hash", "answer")
