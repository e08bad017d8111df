"""Embedders: hashed word n-grams, precomputed vectors, and an endpoint."""

from __future__ import annotations

import http.client
import json
import time
import urllib.request
from collections.abc import Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..stats.hashing import md5_heads

VECTOR = "array<double>"
#: N-grams that are hashed at once.
_GRAMS = 200_000


class Embedder:
    embedder_id = "embedder"
    dim = 0

    def embed(self, df: DataFrame, text: str, out: str = "vec") -> DataFrame:
        raise NotImplementedError


class HashedNgrams(Embedder):
    """Counts of word n-grams hashed by md5 into ``dim`` places, scaled to length 1; empty texts give zeros."""

    def __init__(self, n: int = 1, dim: int = 256) -> None:
        self.n, self.dim = n, dim
        self.embedder_id = f"md5-ngram-{n}-{dim}"

    def many(self, texts: Iterable[str | None]) -> list[np.ndarray]:
        """The vectors of texts, with the hashes of many texts' n-grams at once."""
        out: list[np.ndarray] = []
        grams: list[bytes] = []
        sizes: list[int] = []

        def done() -> None:
            at, places = 0, (md5_heads(grams) % np.uint32(self.dim)).astype(np.int64)
            for n in sizes:
                v = np.bincount(places[at : at + n], minlength=self.dim).astype(float)
                out.append(v / np.sqrt((v**2).sum()) if n else v)
                at += n
            grams.clear()
            sizes.clear()

        for text in texts:
            words = (text or "").lower().split()
            own = words if self.n == 1 else list(map(" ".join, zip(*(words[i:] for i in range(self.n)))))
            grams.extend(map(str.encode, own))
            sizes.append(len(own))
            if len(grams) > _GRAMS:
                done()
        done()
        return out

    def embed(self, df, text, out="vec"):
        many = self.many

        @F.pandas_udf(VECTOR)
        def vectors(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for batch in texts:
                yield pd.Series(many(batch), dtype=object)

        return df.withColumn(out, vectors(text))

    def sql(self, table: str, key: str, text: str) -> str:
        """DuckDB: rows (key, dim, w) of the same vectors, zeros left out."""
        grams = "w" if self.n == 1 else f"[array_to_string(w[i:i+{self.n - 1}], ' ') FOR i IN range(1, len(w) - {self.n} + 2)]"
        return f"""
SELECT key, dim, c / sqrt(sum(c * c) OVER (PARTITION BY key)) AS w FROM (
  SELECT key, ('0x' || substr(md5(g), 1, 8))::BIGINT % {self.dim} AS dim, count(*)::DOUBLE AS c
  FROM (SELECT key, unnest({grams}) AS g FROM (SELECT {key} AS key, list_filter(string_split_regex(lower({text}), '\\s+'), lambda x: x <> '') AS w FROM {table}))
  GROUP BY ALL)"""


class PrecomputedVectors(Embedder):
    """Vectors from a table by key; ``of`` is the key's name in the tables that are embedded, if another one."""

    embedder_id = "precomputed"

    def __init__(self, vectors: DataFrame, key: str, vec: str, of: str | None = None) -> None:
        self.vectors, self.key = vectors.select(F.col(key).alias("_k"), F.col(vec).cast(VECTOR).alias("_v")), of or key

    def embed(self, df, text, out="vec"):
        return df.join(self.vectors, df[self.key] == F.col("_k"), "left").withColumn(out, F.col("_v")).drop("_k", "_v")


class EndpointEmbedder(Embedder):
    """Vectors from an HTTP endpoint: ``{"model", "texts"}`` to ``{"vectors"}``.

    Each task has at most ``max_inflight / tasks`` requests under way; failed ones are
    repeated with a growing pause.
    """

    def __init__(self, url: str, model: str, *, batch_size: int = 64, max_inflight: int = 64, tasks: int = 8, retries: int = 4, timeout: float = 60.0) -> None:
        self.url, self.embedder_id, self.batch_size, self.timeout = url, model, batch_size, timeout
        self.inflight, self.retries = max(1, max_inflight // tasks), retries

    def _ask(self, texts: list[str]) -> list[list[float]]:
        body = json.dumps({"model": self.embedder_id, "texts": texts}).encode()
        for attempt in range(self.retries + 1):
            try:
                with urllib.request.urlopen(urllib.request.Request(self.url, body, {"Content-Type": "application/json"}), timeout=self.timeout) as reply:
                    vectors = json.load(reply)["vectors"]
                if len(vectors) != len(texts):
                    raise ValueError("the endpoint gave another number of vectors")
                return vectors
            except (OSError, http.client.HTTPException, ValueError, KeyError):
                if attempt == self.retries:
                    raise
                time.sleep(min(8.0, 0.05 * 2**attempt))
        raise AssertionError

    def embed(self, df, text, out="vec"):
        ask, size, inflight = self._ask, self.batch_size, self.inflight

        @F.pandas_udf(VECTOR)
        def vectors(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            with ThreadPoolExecutor(inflight) as pool:
                for batch in texts:
                    given = batch.fillna("").tolist()
                    parts = [given[a : a + size] for a in range(0, len(given), size)]
                    yield pd.Series([v for part in pool.map(ask, parts) for v in part], dtype=object)

        return df.withColumn(out, vectors.asNondeterministic()(text))
