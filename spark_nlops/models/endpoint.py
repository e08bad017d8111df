"""A served model behind an HTTP endpoint that takes batches of prompts.

The request is ``{"model", "prompts", "temperature", "logprobs", "options"}``, the reply
``{"answers": [{"text": ..., "logp_true": ...}, ...]}``.  Each task sends at most
``max_inflight / tasks`` requests at a time; failed requests are repeated with a
growing pause.
"""

from __future__ import annotations

import http.client
import json
import time
import urllib.request
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..template import Template
from .base import ModelBackend, comparison_prompt, label_named, label_prompt, list_prompt, pair_name, rendered, rendered_row, reordered


class EndpointModel(ModelBackend):
    def __init__(self, url: str, model: str, *, logprobs: bool = True, max_inflight: int = 64, tasks: int = 8, batch_size: int = 64, retries: int = 4, timeout: float = 60.0, temperature: float = 0.0, demos: tuple[tuple[str, str], ...] = (), reasoning: bool = False) -> None:
        self.url, self.model_id, self.logprobs = url, model, logprobs
        self.max_inflight, self.tasks, self.batch_size = max_inflight, tasks, batch_size
        self.retries, self.timeout, self.temperature = retries, timeout, temperature
        self.demos, self.reasoning = demos, reasoning

    def preamble(self) -> str:
        """Worked demonstrations, and the request to reason first, before every prompt."""
        shown = "".join(f"Input: {a}\nAnswer: {b}\n\n" for a, b in self.demos)
        return shown + ("Reason step by step, then answer on the last line.\n" if self.reasoning else "")

    def _ask(self, prompts: list[str]) -> list[dict]:
        body = json.dumps({"model": self.model_id, "prompts": prompts, "temperature": self.temperature, "logprobs": self.logprobs}).encode()
        for attempt in range(self.retries + 1):
            try:
                request = urllib.request.Request(self.url, body, {"Content-Type": "application/json"})
                with urllib.request.urlopen(request, timeout=self.timeout) as reply:
                    answers = json.load(reply)["answers"]
                if len(answers) != len(prompts):
                    raise ValueError("the endpoint gave another number of answers")
                return answers
            except (OSError, http.client.HTTPException, ValueError, KeyError):  # refused, reset, timed out, or a broken answer
                if attempt == self.retries:
                    raise
                time.sleep(min(8.0, 0.05 * 2**attempt))
        raise AssertionError

    def _prompt(self, df: DataFrame, template: Template) -> Column:
        return template.prompt(df, pair_name) if any(s.side for s in template.slots) else template.prompt(df)

    def _call(self, df: DataFrame, template: Template, out: str) -> DataFrame:
        return self._send(df, self._prompt(df, template), out)

    def _send(self, df: DataFrame, prompt: Column, out: str) -> DataFrame:
        prompt = F.concat(F.lit(self.preamble()), prompt)
        ask, size, inflight = self._ask, self.batch_size, max(1, self.max_inflight // self.tasks)

        def run(prompts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
            with ThreadPoolExecutor(inflight) as pool:
                for batch in prompts:
                    given = [i for i, p in enumerate(batch) if p is not None]
                    parts = [given[a : a + size] for a in range(0, len(given), size)]
                    text: list = [None] * len(batch)
                    logp: list = [None] * len(batch)
                    for part, answers in zip(parts, pool.map(lambda ix: ask([batch.iloc[i] for i in ix]), parts)):
                        for i, x in zip(part, answers):
                            text[i], logp[i] = x.get("text"), x.get("logp_true")
                    yield pd.DataFrame({"text": pd.Series(text, dtype=object), "logp_true": pd.Series(logp, dtype=float)})

        return df.withColumn(out, F.pandas_udf(run, "text string, logp_true double").asNondeterministic()(prompt))

    def text(self, df, template, out="text"):
        return self._call(df, template, "_answer").withColumn(out, F.col("_answer.text")).drop("_answer")

    def label(self, df, template, out="label"):
        got = self._call(df, template, "_answer")
        last = F.lower(F.trim(F.element_at(F.split("_answer.text", "\n"), -1)))
        return got.withColumn(out, F.when(F.col("_answer.text").isNotNull(), last.startswith("true"))).drop("_answer")

    def score(self, df, template, out="score"):
        got = self._call(df, template, "_answer")
        return got.withColumn(out, F.when(F.col("_answer.logp_true").isNotNull(), F.exp(F.least(F.col("_answer.logp_true"), F.lit(0.0))))).drop("_answer")

    def _said(self, df: DataFrame, prompt: Column) -> DataFrame:
        """The last line of each answer, as _said."""
        return self._send(df, prompt, "_answer").withColumn("_said", F.element_at(F.split("_answer.text", "\n"), -1)).drop("_answer")

    def better(self, df, template, a, b, out="better"):
        sides = (rendered(template, lambda c, s=side: F.col(f"{s}.{c}")) for side in (a, b))
        got = self._said(df, F.concat(*[F.lit(p) if isinstance(p, str) else p for p in comparison_prompt(*sides)]))
        return got.withColumn(out, F.upper(F.trim("_said")).startswith("A")).drop("_said")

    def decide(self, template, a, b):
        prompt = self.preamble() + "".join(comparison_prompt(rendered_row(template, a), rendered_row(template, b)))
        return self._ask([prompt])[0]["text"].split("\n")[-1].strip().upper().startswith("A")

    def classify(self, df, template, labels, out="group_label"):
        got = self._said(df, label_prompt(self._prompt(df, template), labels))
        return got.withColumn(out, label_named(F.col("_said"), labels)).drop("_said")

    def order(self, df, template, items, out="ordered"):
        return self._said(df, list_prompt(template, items)).withColumn(out, reordered(items, "_said")).drop("_said")

    def reduce(self, df, template, parts, out="part"):
        got = self._send(df, F.concat(F.lit(template.text + "\n"), F.array_join(parts, "\n---\n")), "_answer")
        return got.withColumn(out, F.col("_answer.text")).drop("_answer")

    def answer(self, df, template, out="answer"):
        """Label and reason side by side."""
        got = self._call(df, template, "_answer")
        lines = F.split("_answer.text", "\n")
        label = F.lower(F.trim(F.element_at(lines, -1))).startswith("true")
        reason = F.array_join(F.slice(lines, F.lit(1), F.greatest(F.size(lines) - 1, F.lit(0))), "\n")
        return got.withColumn(out, F.struct(label.alias("label"), reason.alias("reason"))).drop("_answer")

