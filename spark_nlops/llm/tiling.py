"""Benchmark decontamination by greedy string tiling.

Words of a document and of a benchmark item are numbered.  Runs of ``seed`` words
that both share are joined by hash; for each item that can still reach the
threshold, the longest common run of unmarked words is found with rolling
(Karp-Rabin) hashes, verified and marked on both sides, again and again until no
run of ``seed`` words is left.  The share of the item's words under tiles is its
coverage; since tiles may lie anywhere, reordered passages are caught as well.

The benchmark is shipped to the executors in blocks of at most ``BLOCK_BYTES`` of
text; a larger benchmark takes several passes and no item is left out.  Documents
are never shuffled.

Defined results: null and empty documents and items have no words and coverage
0; items of fewer words than a seed are compared by their whole word sequence;
ties in coverage go to the smallest item id; repeated rows are judged each; null
keys are carried along; very long or repetitive texts take memory in proportion to
their length; without items nothing is contaminated; an empty table gives an empty
table; other columns, whatever their names, are carried along and not read, but
the result's own name must be free.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stage, read_table, small_batches, text_or_empty, trim_memory

SEED, THRESHOLD = 5, 0.6
BLOCK_BYTES = 32_000_000
_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))
words_of = re.compile(r"\w+").findall


def run_hashes(ids: np.ndarray, size: int) -> np.ndarray:
    """Rolling (Karp-Rabin) hashes of every run of ``size`` words: h(x) is the sum of x[k] * base^(size - 1 - k), rolled by prefix sums."""
    if len(ids) < size:
        return np.zeros(0, dtype=np.uint64)
    n = len(ids)
    mixed = ids.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    mixed ^= mixed >> np.uint64(32)
    powers = np.cumprod(np.concatenate((np.ones(1, np.uint64), np.full(n, _INVERSE, dtype=np.uint64))))  # of 1 / base, an odd number modulo 2^64
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(mixed * powers[:n])))
    rises = np.cumprod(np.concatenate((np.ones(1, np.uint64), np.full(n, _BASE, dtype=np.uint64))))
    return (sums[size:] - sums[:-size]) * rises[size - 1 : n]


def _common(doc: np.ndarray, item: np.ndarray, free_doc: np.ndarray, free_item: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Unmarked runs of ``size`` words that both have: their places in the document and hashes there; the item's unmarked runs, sorted by hash, and their hashes."""
    places = np.flatnonzero(_open_runs(free_item, size))
    hashes = run_hashes(item, size)[places]
    order = np.argsort(hashes, kind="stable")
    places, hashes = places[order], hashes[order]
    at = np.flatnonzero(_open_runs(free_doc, size))
    h = run_hashes(doc, size)[at]
    if not len(places) or not len(at):
        return at[:0], h[:0], places, hashes
    first = np.minimum(np.searchsorted(hashes, h), len(hashes) - 1)
    hit = np.flatnonzero(hashes[first] == h)
    return at[hit], h[hit], places, hashes


def tile(doc: np.ndarray, item: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """(document position, item position, length) of the tiles, longest first.

    The longest length at which an unmarked run is common is found by bisection,
    with rolling hashes at each length; runs of that length are compared word by
    word and marked from the left, each with its first free place in the item.
    Memory is linear in both texts, however often they repeat themselves.
    """
    free_doc, free_item = np.ones(len(doc), bool), np.ones(len(item), bool)
    tiles: list[tuple[int, int, int]] = []
    most = min(len(doc), len(item))
    while most >= least:
        low, high = least - 1, most  # a run of low words is common, runs of more than high are not
        while low < high:
            middle = (low + high + 1) // 2
            low, high = (middle, high) if len(_common(doc, item, free_doc, free_item, middle)[0]) else (low, middle - 1)
        if low < least:
            break
        at, h, places, hashes = _common(doc, item, free_doc, free_item, low)
        left = np.searchsorted(hashes, h, "left")
        right = np.searchsorted(hashes, h, "right")
        tried: dict[int, int] = {}  # of each hash, the runs of the item that are taken already
        end = 0
        for a, x, y in zip(at.tolist(), left.tolist(), right.tolist()):
            if a < end:
                continue
            k = tried.get(x, x)
            while k < y and not (free_item[places[k] : places[k] + low].all() and np.array_equal(doc[a : a + low], item[places[k] : places[k] + low])):
                k += 1
            tried[x] = k
            if k < y:
                b = int(places[k])
                tiles.append((a, b, low))
                free_doc[a : a + low] = False
                free_item[b : b + low] = False
                end = a + low
        most = low - 1
    return tiles


def _open_runs(free: np.ndarray, size: int) -> np.ndarray:
    sums = np.concatenate(([0], np.cumsum(free)))
    return sums[size:] - sums[:-size] == size


class Benchmark:
    """One block of items: their word numbers and the table of their seeds."""

    def __init__(self, items: list[tuple[int, str]], seed: int) -> None:
        self.seed = seed
        self.numbers: dict[str, int] = {}
        self.items: list[tuple[int, np.ndarray]] = []
        for key, text in items:
            ids = [self.numbers.setdefault(w, len(self.numbers) + 1) for w in words_of(text.lower())]
            if ids:
                self.items.append((key, np.array(ids, dtype=np.int64)))
        self.sizes = sorted({min(seed, len(ids)) for _, ids in self.items})
        self.tables = {}
        for size in self.sizes:
            hashes, owner, at = [], [], []
            for n, (_, ids) in enumerate(self.items):
                if min(seed, len(ids)) == size:
                    h = window_hashes(ids, size)
                    hashes.append(h)
                    owner.append(np.full(len(h), n))
                    at.append(np.arange(len(h)))
            h = np.concatenate(hashes)
            order = np.argsort(h, kind="stable")
            self.tables[size] = h[order], np.concatenate(owner)[order], np.concatenate(at)[order]

    def compare(self, text: str, threshold: float) -> list[tuple[int, float]]:
        """(item, coverage) of the items whose coverage reaches the threshold."""
        words = words_of(text.lower())
        ids = np.fromiter(map(self.numbers.get, words, repeat(0)), dtype=np.int64, count=len(words))
        if not ids.any():
            return []
        out = []
        for size in self.sizes:
            out += self._compare(ids, size, threshold)
        return out

    def _compare(self, ids: np.ndarray, size: int, threshold: float) -> list[tuple[int, float]]:
        if len(ids) < size:
            return []
        whole = _open_runs(ids > 0, size)
        at = np.flatnonzero(whole)
        if not len(at):
            return []
        h = window_hashes(ids, size)[at]
        table, owner, place = self.tables[size]
        left, right = np.searchsorted(table, h, "left"), np.searchsorted(table, h, "right")
        hit = right > left
        if not hit.any():
            return []
        left, which = np.unique(left[hit], return_index=True)  # each seed of the block once, however often the document has it
        n = right[hit][which] - left
        rows = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(left, n)
        mine, spots = owner[rows], place[rows]
        near = np.zeros(len(ids), bool)  # only words within shared runs can be tiled
        for k in range(size):
            near[at[hit] + k] = True
        border = near & np.concatenate(([True], ~near[:-1]))
        short = ids[near]
        gaps = np.flatnonzero(border[near])[1:]  # keep apart what was apart
        short = np.insert(short, gaps, 0)
        out = []
        for m in np.unique(mine).tolist():
            key, item = self.items[m]
            covered = np.zeros(len(item), bool)
            for k in range(size):
                covered[spots[mine == m] + k] = True
            if covered.sum() < threshold * len(item):
                continue  # tiles lie within shared seeds, so this bounds the coverage
            share = sum(t[2] for t in tile(short, item, size)) / len(item)
            if share >= threshold:
                out.append((key, share))
        return out


def window_hashes(ids: np.ndarray, size: int) -> np.ndarray:
    """Position-free hashes of the runs of ``size`` words (comparable between texts)."""
    out = np.zeros(len(ids) - size + 1, dtype=np.uint64)
    for k in range(size):
        out = out * _BASE + ids[k : len(ids) - size + 1 + k].astype(np.uint64)
        out ^= out >> np.uint64(33)
    return out


def _comparer(spark: SparkSession, items: list[tuple[int | None, str]], seed: int, threshold: float):
    shipped = spark.sparkContext.broadcast(items)

    @F.pandas_udf("array<struct<coverage:double,item:long>>")
    def compare(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        known = Benchmark(shipped.value, seed)
        for batch in texts:
            yield pd.Series([[{"coverage": -c, "item": k} for k, c in known.compare(t, threshold)] for t in batch], dtype=object)
        trim_memory()

    return compare, shipped


def contamination(
    docs: DataFrame,
    benchmark: DataFrame,
    *,
    text: str = "text",
    item_key: str = "item_id",
    item_text: str = "text",
    seed: int = SEED,
    threshold: float = THRESHOLD,
    null_items: bool = False,
    out: str = "nlops_leak",
) -> DataFrame:
    """All columns and ``out`` (not yet a column): array of (item, coverage) that reach the threshold, best first; only the text goes to Python.

    Items with a null key are compared, each text for itself, if null_items is set,
    and left out otherwise.  With several blocks of items each pass is written, so
    that one block at a time is held.
    """
    if out.lower() in map(str.lower, docs.columns):
        raise ValueError(f"the table has a column {out}")
    small_batches(docs.sparkSession)
    items = benchmark.select(F.col(item_key).alias("item"), text_or_empty(item_text).alias("text"))
    items = items if null_items else items.filter("item IS NOT NULL")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-2 * total // BLOCK_BYTES))
    stage = Stage(docs.sparkSession, "tiling") if blocks > 1 else None
    rows = docs.select(F.struct("*").alias("row"), text_or_empty(text).alias("text"), F.array().cast("array<struct<coverage:double,item:long>>").alias("leak"))
    for n in range(blocks):
        part = items if blocks == 1 else items.filter(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == n)
        block = sorted(((r["item"], r["text"]) for r in part.distinct().collect()), key=lambda x: (x[0] is not None, x[0] or 0, x[1]))
        compare, shipped = _comparer(docs.sparkSession, block, seed, threshold)
        rows = rows.select("row", "text", F.concat("leak", compare("text")).alias("leak"))
        if stage:
            rows = stage.keep(rows, f"block{n}")
            shipped.destroy()
            if n:
                stage.drop(f"block{n - 1}")
    ordered = F.sort_array("leak")  # least -coverage first, then item
    best = F.transform(ordered, lambda h: F.struct((-h["coverage"]).alias("coverage"), h["item"].alias("item")))
    return rows.select("row.*", best.alias(out))


def op10_benchmark_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return contamination(docs, read_table(spark, sf_dir, "benchmark"), null_items=True).select(
        "doc_id",
        (F.size("nlops_leak") > 0).alias("contaminated"),
        F.coalesce(F.get("nlops_leak", F.lit(0))["coverage"], F.lit(0.0)).alias("coverage"),
        F.get("nlops_leak", F.lit(0))["item"].alias("item_id"),
        F.size("nlops_leak").alias("n_items"),
    )
