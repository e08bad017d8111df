"""Deterministic models: SQL rules, truth tables, noise on top of another model, and Python callables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..stats.hashing import below, uniform
from ..template import Template
from .base import ModelBackend, comparison_prompt, label_named, label_prompt, list_prompt, null_safe, pair_name, rendered, rendered_row, reordered


class RuleModel(ModelBackend):
    """Answers as SQL expressions over the row's columns.

    ``predicate``/``score`` read the columns (left_* and right_* for pairs),
    ``compare`` reads structs a and b, ``project`` gives a text, ``classifier`` maps
    each label to a score expression, ``reducer`` reads an array named ``parts``.
    ``holds`` says that the predicate is false for all pairs where the first of two
    columns doesn't contain the second, so that joins need not ask about these.
    """

    def __init__(self, predicate=None, score=None, compare=None, project=None, classifier: dict[str, str] | None = None, reducer=None, model_id: str = "rule", holds: tuple[str, str] | None = None) -> None:
        self.holds = holds
        self.predicate, self._score, self.compare, self.project = predicate, score, compare, project
        self.classifier, self.reducer, self.model_id = classifier, reducer, model_id

    def label(self, df, template, out="label"):
        if self.predicate is None:
            self._no("label rows")
        return null_safe(df, template, F.expr(self.predicate).cast("boolean"), out)

    def score(self, df, template, out="score"):
        if self._score is None:
            self._no("score rows")
        return null_safe(df, template, F.expr(self._score).cast("double"), out)

    def text(self, df, template, out="text"):
        if self.project is None:
            self._no("write text")
        return null_safe(df, template, F.expr(self.project).cast("string"), out)

    def better(self, df, template, a, b, out="better"):
        if self.compare is None:
            self._no("compare rows")
        keep = df.columns
        moved = df.withColumns({"a": F.col(a), "b": F.col(b)}).withColumn(out, F.expr(self.compare).cast("boolean"))
        return moved.select(*keep, out)

    def classify(self, df, template, labels, out="group_label"):
        """The label of the highest score; the alphabetically first on ties."""
        rules = self.classifier or self._no("classify rows")
        scored = F.array(*[F.struct((-F.coalesce(F.expr(rules[k]).cast("double"), F.lit(0.0))).alias("s"), F.lit(k).alias("k")) for k in sorted(labels)])
        return null_safe(df, template, F.array_min(scored)["k"], out)

    def order(self, df, template, items, out="ordered"):
        if self.compare is None:
            self._no("order lists")
        return df.withColumn(out, F.expr(f"array_sort(`{items}`, (a, b) -> CASE WHEN a = b THEN 0 WHEN {self.compare} THEN -1 ELSE 1 END)"))

    def reduce(self, df, template, parts, out="part"):
        if self.reducer is None:
            self._no("reduce texts")
        keep = [c for c in df.columns if c != out]
        return df.withColumn("parts", F.col(parts)).withColumn(out, F.expr(self.reducer)).select(*keep, out)


class LookupModel(ModelBackend):
    """Truth from a table: rows whose key is listed with a true value."""

    def __init__(self, truth: DataFrame, key: str, value: str, model_id: str = "lookup") -> None:
        self.truth = truth.select(F.col(key).alias("_key"), F.col(value).cast("boolean").alias("_value")).dropDuplicates(["_key"])
        self.key, self.model_id = key, model_id

    def label(self, df, template, out="label"):
        joined = df.join(self.truth, df[self.key] == F.col("_key"), "left")
        return joined.withColumn(out, F.col("_value")).drop("_key", "_value")


class LookupText(ModelBackend):
    """Text from a table by the row's key, and a SQL expression's where the key isn't listed."""

    def __init__(self, texts: DataFrame, key: str, value: str, otherwise: str = "cast(null as string)", model_id: str = "lookup-text") -> None:
        self.texts = texts.select(F.col(key).alias("_key"), F.col(value).cast("string").alias("_value")).dropDuplicates(["_key"])
        self.key, self.otherwise, self.model_id = key, otherwise, model_id

    def text(self, df, template, out="text"):
        joined = df.join(self.texts, df[self.key] == F.col("_key"), "left")
        return joined.withColumn(out, F.coalesce("_value", F.expr(self.otherwise))).drop("_key", "_value")


class NoisyModel(ModelBackend):
    """Another model whose boolean answers are flipped with a given rate, by a seeded hash of the key or the compared pair."""

    def __init__(self, base: ModelBackend, flip: float, seed: int, key: str, temperature: float = 0.7) -> None:
        self.base, self.flip, self.seed, self.key, self.temperature = base, flip, seed, key, temperature
        self.model_id = f"noisy({base.model_id},{flip},{seed})"

    def label(self, df, template, out="label"):
        got = self.base.label(df, template, out)
        return got.withColumn(out, F.when(uniform(F.col(self.key), self.seed) < self.flip, ~F.col(out)).otherwise(F.col(out)))

    def score(self, df, template, out="score"):
        got = self.base.score(df, template, out)
        return got.withColumn(out, F.when(uniform(F.col(self.key), self.seed) < self.flip, 1 - F.col(out)).otherwise(F.col(out)))

    def better(self, df, template, a, b, out="better"):
        got = self.base.better(df, template, a, b, out)
        # one answer for a pair, whichever way round it is asked
        ka, kb = F.col(f"{a}.{self.key}").cast("string"), F.col(f"{b}.{self.key}").cast("string")
        flips = below(F.concat(F.least(ka, kb), F.lit("|"), F.greatest(ka, kb)), self.seed, self.flip)
        return got.withColumn(out, F.when(flips & (ka != kb), ~F.col(out)).otherwise(F.col(out)))


class VerbalizedConfidence(ModelBackend):
    """A model's stated confidence as score, for models without log-probabilities: the leading number of its text, over 100."""

    def __init__(self, base: ModelBackend) -> None:
        self.base, self.model_id = base, f"stated({base.model_id})"

    def score(self, df, template, out="score"):
        got = self.base.text(df, template, "_said")
        number = F.regexp_extract("_said", r"(\d+(?:\.\d+)?)", 1).cast("double") / 100
        return got.withColumn(out, F.least(F.lit(1.0), F.coalesce(number, F.lit(0.0)))).drop("_said")


def _is_first(said) -> bool:
    """An answer to a comparison: true or A for the first row."""
    return bool(said) if isinstance(said, (bool, int)) else str(said).strip().upper().startswith("A")


class CallableModel(ModelBackend):
    """A Python function from a list of prompts to a list of answers, run in Arrow batches."""

    def __init__(self, answer: Callable[[list[str]], list], model_id: str = "callable", batch_size: int = 64) -> None:
        self.answer, self.model_id, self.batch_size = answer, model_id, batch_size

    def _call(self, df: DataFrame, prompt, kind: str, out: str, post=lambda x: x) -> DataFrame:
        answer, size = self.answer, self.batch_size

        def run(prompts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for batch in prompts:
                given = [i for i, p in enumerate(batch) if p is not None]
                got: list = [None] * len(batch)
                for a in range(0, len(given), size):
                    part = given[a : a + size]
                    for i, x in zip(part, answer([batch.iloc[i] for i in part])):
                        got[i] = post(x)
                yield pd.Series(got, dtype=object)

        # non-deterministic for the optimizer, so that a call is never made twice for one row
        return df.withColumn(out, F.pandas_udf(run, kind).asNondeterministic()(prompt))

    def _prompt(self, df, template: Template):
        return template.prompt(df, pair_name if any(s.side for s in template.slots) else lambda s: s.column)

    def label(self, df, template, out="label"):
        return self._call(df, self._prompt(df, template), "boolean", out, lambda x: None if x is None else bool(x))

    def score(self, df, template, out="score"):
        return self._call(df, self._prompt(df, template), "double", out, lambda x: None if x is None else float(x))

    def text(self, df, template, out="text"):
        return self._call(df, self._prompt(df, template), "string", out, lambda x: None if x is None else str(x))

    def better(self, df, template, a, b, out="better"):
        sides = (rendered(template, lambda c, s=side: F.col(f"{s}.{c}")) for side in (a, b))
        prompt = F.concat(*[F.lit(p) if isinstance(p, str) else p for p in comparison_prompt(*sides)])
        return self._call(df, prompt, "boolean", out, _is_first)

    def decide(self, template, a, b):
        return _is_first(self.answer(["".join(comparison_prompt(rendered_row(template, a), rendered_row(template, b)))])[0])

    def classify(self, df, template, labels, out="group_label"):
        got = self._call(df, label_prompt(self._prompt(df, template), labels), "string", "_said", lambda x: None if x is None else str(x))
        return got.withColumn(out, label_named(F.col("_said"), labels)).drop("_said")

    def order(self, df, template, items, out="ordered"):
        got = self._call(df, list_prompt(template, items), "string", "_said", lambda x: " ".join(map(str, x)) if isinstance(x, (list, tuple)) else str(x))
        return got.withColumn(out, reordered(items, "_said")).drop("_said")

    def reduce(self, df, template, parts, out="part"):
        return self._call(df, F.concat(F.lit(template.text + "\n"), F.array_join(parts, "\n---\n")), "string", out, str)
