"""Toxicity scores of texts whose words may be disguised.

Noisy-channel restoration: a disguised word is a lattice of characters.  A digit
or sign may stand for the letters it resembles, a letter of a run may be a
repetition, a sign between letters may be nothing, and white space between short
pieces (one or two characters, or characters with signs between) may be nothing or a word's end.  The Viterbi path under a character
trigram model, whose counts come from *all* documents, is the restored word.
Words that can't be disguised pass as they are.

Restored texts are scored by a logistic model over the presence of telling words.
The words and weights are learned from a sample of labelled rows, at most about
``train_rows`` (a parameter), drawn by a hash of the key and stratified by label;
the sampling rates are taken out of the intercept again.

Defined results: null and empty texts have no words and get the score of a text
without telling words; with nothing to learn from, every score is 0; equal texts
have equal scores; null keys are scored but never learned from; a key with several
labels counts as toxic if one of them is; an empty table gives an empty table;
other columns are not read.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stage, crc_remainder, read_table, slices, text_or_empty

#: Letters that a digit or sign may stand for.
LOOKALIKES = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "bg", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "il", "|": "il", "+": "t", "(": "c", "<": "c", "€": "e", "£": "l", "¡": "i", "§": "s", "µ": "u", "%": "x", "#": "h", "*": "aeiou", "&": "a", "^": "a",
}
FILLERS = set(".-_*~'`,:;/\\|^+=·•")
#: Costs (negative log-likelihoods) of the channel.
SUBSTITUTED, FILLED, DOUBLED, REPEATED, CLOSED, LITERAL = 0.7, 0.5, 6.5, 0.6, 2.5, 8.0
CODES = 64  # 0 is a word's border, 1 to 26 are a to z, then hashed other letters
WORD_BITS = 20
#: Restored words remembered by a worker.
MEMO_ENTRIES = 300_000
CLEAN = re.compile(r"[^\W\d_]+").fullmatch
DOUBLE = re.compile(r"(.)\1")
#: A piece of a word in pieces: one or two characters, or single characters with signs between them.
FRAGMENT = re.compile(r"\S{1,2}|\S(?:[-._*~'`,:;/\\|^+=·•]+\w)+").fullmatch
#: Longest run of fragments that is remembered.
MEMO_LENGTH = 40
EDGES = "\"'.,:;()[]{}«»„“”‘’?¿-–—_*~`/\\"


def code_of(letter: str) -> int:
    c = ord(letter)
    return c - 96 if 97 <= c <= 122 else 27 + c % (CODES - 27)


def _codes(text: str) -> np.ndarray:
    """Codes of a lower-cased text; whatever is no letter is a border."""
    c = np.frombuffer(text.lower().encode("utf-32-le"), dtype=np.uint32)
    small = (c >= 97) & (c <= 122)
    other = (c >= 0xAA) & ~np.isin(c, _NOT_LETTERS)
    return np.where(small, c - 96, np.where(other, 27 + c % (CODES - 27), 0)).astype(np.int64)


_NOT_LETTERS = np.array([i for i in range(0xAA, 0x3000) if not chr(i).isalpha()], dtype=np.uint32)


def trigram_counts(docs: DataFrame, *, text: str = "text") -> np.ndarray:
    """Counts of all documents' character trigrams; one table of fixed size leaves each task."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(CODES**3, dtype=np.int64)
        for batch in batches:
            for a, b in slices(batch["text"].map(len).tolist(), 1_000_000):
                c = np.concatenate([np.concatenate((_codes(t), (0, 0))) for t in batch["text"].iloc[a:b]])
                c = np.concatenate(((0, 0), c))
                total += np.bincount((c[:-2] * CODES + c[1:-1]) * CODES + c[2:], minlength=CODES**3)
        at = np.flatnonzero(total)
        yield pd.DataFrame({"gram": at, "n": total[at]})

    found = docs.select(text_or_empty(text).alias("text")).mapInPandas(run, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(CODES**3, dtype=np.int64)
    out[found["gram"].to_numpy(dtype=int)] = found["n"].to_numpy()
    return out


def trigram_costs(counts: np.ndarray, weight: float = 4.0) -> np.ndarray:
    """Negative log-probabilities, trigrams backed by bigrams backed by single characters."""
    n3 = counts.reshape(CODES, CODES, CODES).astype(float)
    n2 = n3.sum(axis=0)
    n1 = n2.sum(axis=0)
    p1 = (n1 + 0.5) / (n1.sum() + 0.5 * CODES)
    p2 = (n2 + weight * p1) / (n2.sum(axis=1, keepdims=True) + weight)
    p3 = (n3 + weight * p2[None]) / (n3.sum(axis=2, keepdims=True) + weight)
    return -np.log(p3)


class Restorer:
    """Restores words by the cheapest path through their lattices."""

    def __init__(self, costs: np.ndarray) -> None:
        self.costs = costs.reshape(-1).tolist()
        self.memo: dict[str, str] = {}

    @staticmethod
    def disguised(word: str) -> bool:
        if CLEAN(word):
            return DOUBLE.search(word) is not None
        return any(map(str.isalpha, word)) or any(c in "@$" for c in word)

    def lattice(self, text: str) -> Iterator[list[tuple[str, float]]]:
        """For each character what it may stand for, with costs; an empty string is nothing."""
        before, run = "", 0
        for at, c in enumerate(text):
            arcs: list[tuple[str, float]] = []
            if c == " ":
                arcs = [("", FILLED), (" ", CLOSED)]
            elif c.isalpha():
                arcs = [(c, 0.0)]
            else:
                arcs = [(x, SUBSTITUTED + (len(LOOKALIKES[c]) - 1) * 0.3) for x in LOOKALIKES.get(c, "")]
                if c in FILLERS:
                    arcs.append(("", FILLED))
                arcs.append((c, LITERAL))
            run = run + 1 if c == before else 1
            if run > 1 and c != " ":
                # the second of a run may belong there; of longer runs more is repetition
                arcs.append(("", REPEATED if text[max(0, at - run + 1) :].startswith(c * 3) else DOUBLED))
            yield arcs
            before = c

    def decode(self, text: str) -> str:
        costs = self.costs
        # state: the last two codes; value: cost and the path's last link
        states: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
        for arcs in self.lattice(text):
            moved: dict[tuple[int, int], tuple[float, tuple | None]] = {}
            for (a, b), (cost, path) in states.items():
                for letter, price in arcs:
                    if not letter:
                        state, total, link = (a, b), cost + price, path
                    else:
                        c = 0 if letter == " " or not letter.isalpha() else code_of(letter)
                        state, total, link = (b, c), cost + price + costs[(a * CODES + b) * CODES + c], (letter, path)
                    old = moved.get(state)
                    if old is None or total < old[0]:
                        moved[state] = (total, link)
            states = moved
        _, path = min(((cost + costs[(a * CODES + b) * CODES], path) for (a, b), (cost, path) in states.items()), key=lambda x: x[0])
        letters = []
        while path is not None:
            letters.append(path[0])
            path = path[1]
        return "".join(reversed(letters))

    def word(self, raw: str) -> str:
        found = self.memo.get(raw)
        if found is None:
            if len(self.memo) >= MEMO_ENTRIES:
                self.memo.clear()
            core = raw.strip(EDGES).rstrip("!").strip(EDGES)  # closing exclamation marks are punctuation
            found = self.memo[raw] = self.decode(core) if self.disguised(core) else core
        return found

    def words(self, text: str) -> list[str]:
        """The restored words of a text, in order, in lower case and without punctuation around them."""
        text = text.lower()
        raw = text.split()
        return list(map(self.word, raw)) + [w for run in fragment_runs(raw) for w in self.run(run)]

    def run(self, raw: str) -> list[str]:
        """The words that a run of fragments, joined by single spaces, is restored to."""
        found = self.memo.get(raw)
        if found is None:
            found = self.decode(raw.strip(EDGES))
            if len(raw) <= MEMO_LENGTH:
                if len(self.memo) >= MEMO_ENTRIES:
                    self.memo.clear()
                self.memo[raw] = found
        return found.split()


def fragment_runs(words: list[str]) -> Iterator[str]:
    """Maximal runs of two or more fragments with three or more characters, whatever white space was between them."""
    start = None
    for at, word in enumerate(words):
        if len(word) <= 2 or (not CLEAN(word) and FRAGMENT(word.strip(EDGES))):
            start = at if start is None else start
        elif start is not None:
            if at - start > 1 and sum(map(len, words[start:at])) > 2:
                yield " ".join(words[start:at])
            start = None
    if start is not None and len(words) - start > 1 and sum(map(len, words[start:])) > 2:
        yield " ".join(words[start:])


def word_features(words: list[str]) -> np.ndarray:
    """Hash numbers of the distinct words."""
    return np.array(sorted({zlib.crc32(w.encode()) >> (32 - WORD_BITS) for w in words if w}), dtype=np.int32)


@dataclass
class ToxicityModel:
    costs: np.ndarray
    weights: dict[int, float] = field(default_factory=dict)
    bias: float = -50.0

    def score(self, words: list[str]) -> float:
        z = self.bias + sum(self.weights.get(int(f), 0.0) for f in word_features(words)) if self.weights else self.bias
        return float(1.0 / (1.0 + np.exp(-np.clip(z, -700, 700)))) if z > -50 else 0.0


def _fit_logistic(x: np.ndarray, y: np.ndarray, penalty: float = 0.3, rounds: int = 30) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the last column is the intercept, without penalty."""
    w = np.zeros(x.shape[1])
    ridge = np.full(x.shape[1], penalty)
    ridge[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + np.diag(ridge), x.T @ (y - p) - ridge * w)
        w += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-6:
            break
    return w


def telling_words(rows: DataFrame, most: int = 400) -> list[int]:
    """Features whose presence speaks for label 1: likelihood ratio, lift and support are all large. Rows have y and f; counts are aggregated in Spark."""
    n1, n0 = rows.agg(F.sum("y"), F.sum(1 - F.col("y"))).first()
    if not n1 or not n0:
        return []
    share = n1 / (n1 + n0)
    a, b = F.col("a").cast("double"), F.col("b").cast("double")
    ratio = 2 * (a * F.log(a / ((a + b) * share)) + F.when(b > 0, b * F.log(b / ((a + b) * (1 - share)))).otherwise(0.0))
    lift = (a / n1) / ((b + 0.5) / n0)
    counts = rows.select("y", F.explode("f").alias("f")).groupBy("f").agg(F.sum("y").alias("a"), F.sum(1 - F.col("y")).alias("b")).filter("a >= 3")
    best = counts.withColumns({"ratio": ratio, "lift": lift}).filter("lift > 4 AND ratio > 12").orderBy(F.desc("ratio"), "f").limit(most)
    return sorted(r["f"] for r in best.select("f").collect())


def train(
    docs: DataFrame, labels: DataFrame, *, key: str = "doc_id", text: str = "text", label: str = "toxic", lm_docs: DataFrame | None = None, train_rows: int = 16_000
) -> ToxicityModel:
    """Learn from rows with a label; the character model from all of lm_docs (by default docs)."""
    model = ToxicityModel(trigram_costs(trigram_counts(lm_docs if lm_docs is not None else docs, text=text)))
    known = labels.filter(F.col(key).isNotNull() & F.col(label).isNotNull()).groupBy(F.col(key).alias("key")).agg((F.max(label) > 0).cast("int").alias("y"))
    sizes = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    if not sizes.get(1) or not sizes.get(0):
        return model
    rates = {y: min(1.0, train_rows / 2 / n) for y, n in sizes.items()}
    draw = F.pmod(F.xxhash64(F.lit(11), "key"), F.lit(1_000_000)) / F.lit(1_000_000.0)
    sample = known.filter(draw < F.when(F.col("y") == 1, rates[1]).otherwise(rates[0]))
    restorer_costs = docs.sparkSession.sparkContext.broadcast(model.costs.astype(np.float32))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        restorer = Restorer(restorer_costs.value)
        for batch in batches:
            yield pd.DataFrame({"y": batch["y"].array, "f": [word_features(restorer.words(t)) for t in batch["text"]]})

    # the sample has at most about train_rows small rows, so it may be broadcast
    picked = docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).join(F.broadcast(sample), "key")
    rows = Stage(docs.sparkSession, "toxicity").keep(picked.mapInPandas(run, "y int, f array<int>"), "sample")
    chosen = telling_words(rows)
    # only which of the telling words a row has goes to the driver
    got = rows.select("y", F.array_intersect("f", F.array(*[F.lit(f) for f in chosen]).cast("array<int>")).alias("f")).toPandas()
    y = got["y"].to_numpy(dtype=int)
    x = np.zeros((len(got), len(chosen) + 1))
    x[:, -1] = 1
    for i, f in enumerate(got["f"]):
        x[i, np.searchsorted(chosen, f)] = 1
    order = np.lexsort((*x.T, y))  # sums in a fixed order, wherever the rows came from
    w = _fit_logistic(x[order], y[order].astype(float))
    model.weights = dict(zip(chosen, w[:-1].tolist()))
    model.bias = float(w[-1] + np.log(rates[0] / rates[1]))
    return model


def score(docs: DataFrame, model: ToxicityModel, *, key: str = "doc_id", text: str = "text", keep_text: bool = True) -> DataFrame:
    """key, score and, if kept, the restored text of every whole text."""
    shipped = docs.sparkSession.sparkContext.broadcast((model.costs.astype(np.float32), model.weights, model.bias))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        costs, weights, bias = shipped.value
        restorer, own = Restorer(costs), ToxicityModel(costs, weights, bias)
        for batch in batches:
            scores, restored = [], []
            for t in batch["text"]:
                words = restorer.words(t)
                scores.append(own.score(words))
                if keep_text:
                    restored.append(" ".join(words))
            yield pd.DataFrame({"key": batch["key"].array, "score": scores} | ({"restored": restored} if keep_text else {}))

    kind = docs.schema[key].dataType.simpleString()
    schema = f"key {kind}, score double" + ", restored string" * keep_text
    return docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInPandas(run, schema).withColumnRenamed("key", key)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = read_table(spark, sf_dir, "labels").select("doc_id", "toxic").filter(crc_remainder("doc_id", 5) != 0)
    model = train(docs, labels)
    return score(docs, model, keep_text=False).select(
        "doc_id",
        F.coalesce(crc_remainder("doc_id", 5) == 0, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
    )
