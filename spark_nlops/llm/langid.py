"""Language identification by sparse multinomial logistic regression.

Features are hashed character 1- to 3-grams of the lower-cased text, weighted by
TF-IDF and scaled to a fixed sum.  Document frequencies come from *all* labelled
rows that may be learned from.  The weights are fitted by follow-the-regularised-
leader with elastic-net penalties on a stratified sample of at most about
``train_rows`` of those rows (a parameter; an equal share for each language), and
a temperature is fitted on a fifth of the sample that the weights never saw.

As the features are linear in the counts, a text is scored by gathering rows of
one small table, whatever its length.

Defined results: null and empty texts and texts without a letter are ``und``
with score 0, as is everything if there is nothing to learn from; ties go to the
alphabetically first language; null keys are neither learned from nor held out;
rows without a language are predicted but not learned from; very long texts are
read whole, in parts; repeated rows count each; an empty table gives an empty
table; other columns, whatever their names, are carried along and not read, but the
result's own name must be free.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_remainder, read_table, small_batches, text_or_empty, trim_memory

ORDERS, BITS = 3, 15
FEATURES = ORDERS << BITS
SCALE = 40.0
#: Characters turned into features together.
PART = 1 << 18
UNDETERMINED = "und"
_MULTIPLIERS = [np.uint32(x) for x in (2654435761, 2246822519, 3266489917)]


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def features(text: str) -> np.ndarray:
    """Feature numbers of all n-grams of a text (repeats included)."""
    codes = np.frombuffer(text.lower().encode("utf-32-le"), dtype=np.uint32)
    parts = []
    for n in range(ORDERS):
        if len(codes) <= n:
            break
        h = codes[: len(codes) - n] * _MULTIPLIERS[0]
        for i in range(1, n + 1):
            h = (h ^ (h >> np.uint32(15))) * _MULTIPLIERS[i] + codes[i : len(codes) - n + i] * _MULTIPLIERS[0]
        h ^= h >> np.uint32(16)
        parts.append(((h * _MULTIPLIERS[1]) >> np.uint32(32 - BITS)).astype(np.int32) + (n << BITS))
    return np.concatenate(parts) if parts else np.zeros(0, np.int32)


def text_parts(text: str) -> Iterator[str]:
    """A long text in overlapping parts that hold each 3-gram once (shorter grams at the borders count twice)."""
    for a in range(0, max(1, len(text)), PART):
        yield text[a : a + PART + ORDERS - 1]


@dataclass
class LanguageModel:
    languages: list[str]
    table: np.ndarray  # FEATURES x (1 + languages): idf, then idf * weight
    bias: np.ndarray
    temperature: float

    def logits(self, text: str) -> np.ndarray:
        total = np.zeros(self.table.shape[1])
        for part in text_parts(text):
            total += self.table[features(part)].sum(axis=0, dtype=np.float64)
        return total[1:] * (SCALE / max(total[0], 1e-9)) + self.bias

    def predict(self, text: str) -> tuple[str, float]:
        if not self.languages or not has_letter(text):
            return UNDETERMINED, 0.0
        z = self.logits(text) / self.temperature
        p = np.exp(z - z.max())
        p /= p.sum()
        best = int(p.argmax())
        return self.languages[best], float(p[best])


def sparse_row(text: str, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    counts = np.zeros(FEATURES, dtype=np.float64)
    for part in text_parts(text):
        counts += np.bincount(features(part), minlength=FEATURES)
    at = np.flatnonzero(counts)
    x = counts[at] * idf[at]
    return at, x * (SCALE / max(x.sum(), 1e-9))


class ProximalFit:
    """Follow-the-regularised-leader (proximal) for several classes; weights are made from the running sums when needed."""

    def __init__(self, classes: int, alpha: float, beta: float, l1: float, l2: float) -> None:
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((FEATURES + 1, classes)), np.zeros((FEATURES + 1, classes))

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, label: int) -> None:
        at, x = np.append(at, FEATURES), np.append(x, 1.0)  # the last row is the bias
        w = self.weights(at)
        s = x @ w
        p = np.exp(s - s.max())
        p /= p.sum()
        p[label] -= 1.0
        g = x[:, None] * p[None, :]
        step = (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.alpha
        self.z[at] += g - step * w
        self.n[at] += g * g


def fit_temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature of least negative log-likelihood, by a refined grid in the logarithm."""
    if not len(logits):
        return 1.0

    def loss(t: float) -> float:
        z = logits / t
        z = z - z.max(axis=1, keepdims=True)
        return float(np.mean(np.log(np.exp(z).sum(axis=1)) - z[np.arange(len(z)), labels]))

    low, high = np.log(0.05), np.log(20.0)
    for _ in range(4):
        grid = np.linspace(low, high, 21)
        best = int(np.argmin([loss(float(np.exp(g))) for g in grid]))
        low, high = grid[max(0, best - 1)], grid[min(20, best + 1)]
    return float(np.exp((low + high) / 2))


def document_frequencies(rows: DataFrame) -> tuple[int, np.ndarray]:
    """Number of rows and, for each feature, of rows that have it; column text. One vector leaves each task."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, counts = 0, np.zeros(FEATURES, dtype=np.int64)
        seen = np.zeros(FEATURES, dtype=bool)
        for batch in batches:
            for text in batch["text"]:
                for part in text_parts(text):
                    seen[features(part)] = True
                at = np.flatnonzero(seen)
                counts[at] += 1
                seen[at] = False
                total += 1
        at = np.flatnonzero(counts)
        yield pd.DataFrame({"feature": np.append(at, -1), "n": np.append(counts[at], total)})

    found = rows.mapInPandas(run, "feature int, n long").groupBy("feature").agg(F.sum("n").alias("n")).toPandas()  # at most FEATURES + 1 rows
    out = np.zeros(FEATURES + 1, dtype=np.int64)
    out[found["feature"].to_numpy()] = found["n"].to_numpy()  # -1 is the last place
    return int(out[-1]), out[:-1]


def train(
    docs: DataFrame, *, key: str = "doc_id", text: str = "text", lang: str = "lang", train_rows: int = 4000, epochs: int = 3, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.002, l2: float = 0.001
) -> LanguageModel:
    """Learn from all given rows that have a key, a language and a letter; the weights from a sample of about train_rows."""
    small_batches(docs.sparkSession)
    rows = docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text"), F.col(lang).cast("string").alias("lang")).filter(
        "key IS NOT NULL AND lang IS NOT NULL AND lang <> '' AND text RLIKE '\\\\p{L}'"
    )
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).limit(1025).collect()}
    if not sizes:
        return LanguageModel([], np.zeros((FEATURES, 1), np.float32), np.zeros(0), 1.0)
    if len(sizes) > 1024:
        raise ValueError("more than 1024 languages")
    languages = sorted(sizes)
    share = max(1, train_rows // len(languages))
    total, found = document_frequencies(rows.select("text"))
    idf = np.log((1 + total) / (1 + found)) + 1.0
    # an equal share for each language, drawn by a seeded hash of the key
    draw = F.pmod(F.xxhash64(F.lit(7), F.col("key")), F.lit(1_000_000)) / F.lit(1_000_000.0)
    rate = F.element_at(F.create_map(*[F.lit(x) for k in languages for x in (k, min(1.0, share / sizes[k]))]), F.col("lang"))
    sample = rows.filter(draw < rate).select("key", "text", "lang").toPandas().sort_values("key", kind="stable")
    order = np.random.default_rng(3).permutation(len(sample))
    held = order[: len(sample) // 5] if len(sample) >= 50 else order[:0]
    used = order[len(held) :]
    number = {k: i for i, k in enumerate(languages)}
    texts, labels = sample["text"].tolist(), np.array([number[k] for k in sample["lang"]])
    fit = ProximalFit(len(languages), alpha, beta, l1, l2)
    for _ in range(epochs):
        for i in used:
            fit.learn(*sparse_row(texts[i], idf), labels[i])
    weights = fit.weights()
    table = np.concatenate((idf[:, None], idf[:, None] * weights[:-1]), axis=1).astype(np.float32)
    model = LanguageModel(languages, table, weights[-1], 1.0)
    model.temperature = fit_temperature(np.array([model.logits(texts[i]) for i in held]), labels[held])
    return model


def predict(docs: DataFrame, model: LanguageModel, *, text: str = "text", out: str = "nlops_language") -> DataFrame:
    """All columns and a struct column ``out`` (lang, score), which must not be a column yet; only the text goes to Python."""
    if out.lower() in map(str.lower, docs.columns):
        raise ValueError(f"the table has a column {out}")
    small_batches(docs.sparkSession)
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # FEATURES x (1 + languages) floats

    @F.pandas_udf("lang string, score double")
    def language(texts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        model = shipped.value
        for batch in texts:
            yield pd.DataFrame([model.predict(t) for t in batch], columns=["lang", "score"])
        trim_memory()

    return docs.withColumn(out, language(text_or_empty(text)))


def learnable(docs: DataFrame, *, key: str = "doc_id", modulus: int = 4, remainder: int = 2) -> DataFrame:
    return docs.filter(crc_remainder(key, modulus) != remainder)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(learnable(docs))
    return predict(docs.select("doc_id", "text"), model).select(
        "doc_id",
        F.coalesce(crc_remainder("doc_id", 4) == 2, F.lit(False)).alias("held_out"),
        F.col("nlops_language.lang").alias("lang_pred"),
        F.col("nlops_language.score").alias("score"),
    )
