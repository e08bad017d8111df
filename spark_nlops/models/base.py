"""The model plug-in interface.

A model answers questions about rows by adding columns.  Operators never call a
model row by row; they hand over a DataFrame and get it back with the answer, so a
rule model stays inside code generation while a served model runs in Arrow batches.
Boolean answers are null where a slot is null; such rows are not asked about.
"""

from __future__ import annotations

from abc import ABC

from pyspark.sql import Column, DataFrame

from ..template import Template


class ModelBackend(ABC):
    """Override what the model can do; the rest refuses."""

    model_id = "model"
    batch_size = 64
    temperature = 0.0

    def _no(self, what: str):
        raise NotImplementedError(f"{type(self).__name__} doesn't {what}")

    def label(self, df: DataFrame, template: Template, out: str = "label") -> DataFrame:
        """A boolean answer for each row (pair templates: columns are named left_* and right_*)."""
        self._no("label rows")

    def score(self, df: DataFrame, template: Template, out: str = "score") -> DataFrame:
        """The probability (or another monotone score, 0 to 1) of a true answer."""
        self._no("score rows")

    def text(self, df: DataFrame, template: Template, out: str = "text") -> DataFrame:
        self._no("write text")

    def better(self, df: DataFrame, template: Template, a: str, b: str, out: str = "better") -> DataFrame:
        """Whether struct column a ranks before struct column b."""
        self._no("compare rows")

    def classify(self, df: DataFrame, template: Template, labels: list[str], out: str = "group_label") -> DataFrame:
        self._no("classify rows")

    def order(self, df: DataFrame, template: Template, items: str, out: str = "ordered") -> DataFrame:
        """The structs of an array column, best first."""
        self._no("order lists")

    def decide(self, template: Template, a: dict, b: dict) -> bool:
        """Whether row a ranks before row b; one call at a time, for algorithms that can't ask in batches."""
        self._no("compare single rows")

    def reduce(self, df: DataFrame, template: Template, parts: str, out: str = "part") -> DataFrame:
        """One text for each row's array of texts."""
        self._no("reduce texts")


def rendered(template: Template, field) -> Column:
    """The template with the columns that ``field`` gives for its slots; nulls are shown as nothing."""
    from pyspark.sql import functions as F

    parts = [F.lit(p) if isinstance(p, str) else F.coalesce(field(p.column).cast("string"), F.lit("")) for p in template.parts]
    return F.concat(*parts) if parts else F.lit("")


def rendered_row(template: Template, row: dict) -> str:
    return "".join(p if isinstance(p, str) else "" if row[p.column] is None else str(row[p.column]) for p in template.parts)


def comparison_prompt(a, b) -> list:
    """The parts of the question which of two rendered rows ranks first."""
    return ["A: ", a, "\nB: ", b, "\nWhich fits better? Answer A or B."]


def list_prompt(template: Template, items: str) -> Column:
    """The numbered items of an array column, and the request to order them."""
    from pyspark.sql import functions as F

    lines = F.transform(F.col(items), lambda x, i: F.concat(F.lit("["), i.cast("string"), F.lit("] "), rendered(template, lambda c: x[c])))
    return F.concat(F.array_join(lines, "\n"), F.lit("\nOrder the numbers, best first."))


def reordered(items: str, said: str) -> Column:
    """The items in the order of the numbers in an answer; numbers that are no items, or come again, are passed over, and what isn't named comes last."""
    from pyspark.sql import functions as F

    named = F.filter(F.transform(F.regexp_extract_all(F.coalesce(said, F.lit("")), F.lit(r"(\d{1,9})"), 1), lambda x: x.cast("int")), lambda x: x < F.size(items))
    rest = F.when(F.size(items) > 0, F.sequence(F.lit(0), F.size(items) - 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(F.array_distinct(F.concat(named, rest)), lambda i: F.get(F.col(items), i))


def label_named(said: Column, labels: list[str]) -> Column:
    """The label that an answer is, but for case and white space around it; null if it is none."""
    from pyspark.sql import functions as F

    table = F.create_map(*[F.lit(x) for k in labels for x in (k.strip().lower(), k)])
    return F.element_at(table, F.lower(F.trim(said)))


def label_prompt(prompt: Column, labels: list[str]) -> Column:
    from pyspark.sql import functions as F

    return F.concat(prompt, F.lit("\nLabels: " + "; ".join(labels) + "\nAnswer with one label."))


def pair_name(slot) -> str:
    return f"{slot.side}_{slot.column}"


def null_safe(df: DataFrame, template: Template, answer: Column, out: str) -> DataFrame:
    from pyspark.sql import functions as F

    pair = any(s.side for s in template.slots)
    null = template.has_null(pair_name) if pair else template.has_null()
    return df.withColumn(out, F.when(~null, answer))
