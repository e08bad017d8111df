"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

Every merge rank has a bucket of linked-list positions (the left token of a
pair).  A three-level bitmap says which buckets hold entries; find-first-set on
its words gives the next rank.  Merging rewrites the neighbours' pairs and
pushes them to their new buckets; older entries stay where they are and are
skipped when popped, because the position's current rank differs.

Two drivers share the queue:

* ``Codec.encode_many`` merges many pre-tokens at once: their bytes form one
  linked list with barriers, and all live positions of the next rank are merged
  together in array operations.  A merge that gives rise to a *lower* rank than
  its own would have to run before the rest of its bucket; such pre-tokens are
  noted and encoded again one merge at a time.
* ``Codec.encode_one`` pops single positions, leftmost first within a rank.

Both cost O(n) pops for a pre-token of n bytes, so very long pre-tokens do not
turn quadratic.

Defined results: a null text counts as empty; the empty text has no ids and
decodes to no bytes; repeated rows and ties are encoded each for itself; null
keys are carried along; an empty table gives an empty table; other columns of
the input are not read.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator
from heapq import heappop, heappush

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table, slices, small_batches, text_or_empty, trim_memory

NONE = np.int32(2**31 - 1)
#: Characters of text tokenised together; bounds a worker's memory.
BATCH_CHARS = 2_000_000
#: Pre-tokens remembered within a task, and the longest one remembered (characters).
MEMO_ENTRIES, MEMO_CHARS = 150_000, 64


class RankQueue:
    """Buckets by rank below a three-level bitmap of 64-bit words."""

    __slots__ = ("buckets", "leaf", "mid", "top")

    def __init__(self, ranks: int) -> None:
        self.buckets: dict[int, list[int]] = {}
        self.leaf = [0] * ((ranks >> 6) + 1)
        self.mid = [0] * ((ranks >> 12) + 1)
        self.top = 0

    def open_bucket(self, rank: int) -> list[int]:
        bucket = self.buckets.get(rank)
        if bucket is None:
            bucket = self.buckets[rank] = []
            self.leaf[rank >> 6] |= 1 << (rank & 63)
            self.mid[rank >> 12] |= 1 << ((rank >> 6) & 63)
            self.top |= 1 << (rank >> 12)
        return bucket

    def first(self) -> int:
        """The least rank that has entries, or -1."""
        if not self.top:
            return -1
        a = (self.top & -self.top).bit_length() - 1
        b = self.mid[a]
        b = (a << 6) | ((b & -b).bit_length() - 1)
        c = self.leaf[b]
        return (b << 6) | ((c & -c).bit_length() - 1)

    def close(self, rank: int) -> list[int]:
        bucket = self.buckets.pop(rank)
        word = rank >> 6
        self.leaf[word] &= ~(1 << (rank & 63))
        if not self.leaf[word]:
            self.mid[word >> 6] &= ~(1 << (word & 63))
            if not self.mid[word >> 6]:
                self.top &= ~(1 << (word >> 6))
        return bucket


class Codec:
    def __init__(self, rank_file: bytes, pattern: str) -> None:
        self.pattern = regex.compile(pattern)
        self.ranks: dict[bytes, int] = {}
        for line in rank_file.splitlines():
            if line.strip():
                token, rank = line.split()
                self.ranks[base64.b64decode(token)] = int(rank)
        self.size = max(self.ranks.values()) + 1
        self.tokens = [b""] * self.size
        for token, rank in self.ranks.items():
            self.tokens[rank] = token
        self.names = [str(i) for i in range(self.size)]
        self.byte_ids = np.array([self.ranks[bytes([b])] for b in range(256)], dtype=np.int32)
        pairs = {}
        for token, rank in self.ranks.items():
            for cut in range(1, len(token)):
                left, right = self.ranks.get(token[:cut]), self.ranks.get(token[cut:])
                if left is not None and right is not None:
                    pairs[(left << 20) | right] = rank
        self.pairs = pairs
        keys = np.fromiter(pairs, dtype=np.int64, count=len(pairs))
        order = np.argsort(keys)
        self.pair_keys = keys[order]
        self.pair_ranks = np.fromiter(pairs.values(), dtype=np.int32, count=len(pairs))[order]
        self.packed: dict[str, bytes] = {}  # ids of a pre-token as 32-bit integers

    # --- pair lookups -------------------------------------------------------------
    def _pair_rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = (left.astype(np.int64) << 20) | right
        at = np.searchsorted(self.pair_keys, key)
        at[at == len(self.pair_keys)] = 0
        return np.where(self.pair_keys[at] == key, self.pair_ranks[at], NONE)

    # --- one pre-token, one merge at a time ----------------------------------------
    def encode_one(self, piece: bytes) -> tuple[int, ...]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return (whole,)
        n = len(piece)
        if n == 0:
            return ()
        ids = [int(self.byte_ids[b]) for b in piece]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        after[-1] = -1
        get, none = self.pairs.get, -1
        rank = [none] * n
        queue = RankQueue(self.size)
        for i in range(n - 1):
            r = rank[i] = get((ids[i] << 20) | ids[i + 1], none)
            if r >= 0:
                queue.open_bucket(r).append(i)  # ascending, hence a heap
        while (r := queue.first()) >= 0:
            bucket = queue.buckets[r]
            i = heappop(bucket)
            if not bucket:
                queue.close(r)
            if rank[i] != r:
                continue
            j = after[i]
            k = after[j]
            ids[i], ids[j], rank[j] = r, -1, none
            after[i] = k
            rank[i] = none
            if k >= 0:
                before[k] = i
                rank[i] = new = get((r << 20) | ids[k], none)
                if new >= 0:
                    heappush(queue.open_bucket(new), i)
            h = before[i]
            if h >= 0:
                rank[h] = new = get((ids[h] << 20) | r, none)
                if new >= 0:
                    heappush(queue.open_bucket(new), h)
        return tuple(x for x in ids if x >= 0)

    # --- many pre-tokens together ---------------------------------------------------
    def encode_many(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        out: list[tuple[int, ...] | None] = [(r,) if (r := self.ranks.get(p)) is not None else (() if not p else None) for p in pieces]
        todo = [i for i, x in enumerate(out) if x is None]
        if not todo:
            return out
        lengths = np.array([len(pieces[i]) for i in todo])
        ends = np.cumsum(lengths)
        starts = ends - lengths
        n = int(ends[-1])
        ids = self.byte_ids[np.frombuffer(b"".join([pieces[i] for i in todo]), dtype=np.uint8)]
        after = np.arange(1, n + 1)
        after[ends - 1] = -1
        before = np.arange(-1, n - 1)
        before[starts] = -1
        rank = np.full(n, NONE, dtype=np.int32)
        inner = np.flatnonzero(after >= 0)
        rank[inner] = self._pair_rank(ids[inner], ids[inner + 1])
        queue = RankQueue(self.size)
        live = np.flatnonzero(rank != NONE)
        live = live[np.argsort(rank[live], kind="stable")]
        cuts = np.flatnonzero(np.diff(rank[live])) + 1
        for group in np.split(live, cuts) if len(live) else []:
            queue.open_bucket(int(rank[group[0]])).extend(group.tolist())
        redo: list[np.ndarray] = []
        open_bucket = queue.open_bucket
        while (r := queue.first()) >= 0:
            at = np.array(queue.close(r))
            at = at[rank[at] == r]
            if len(at) > 1:
                at.sort()
                twice = at[1:] == at[:-1]
                if twice.any():
                    at = at[np.append(True, ~twice)]
            elif not len(at):
                continue
            chained = after[at[:-1]] == at[1:]
            if chained.any():  # the same pair overlaps itself: take every other one from the left
                keep, last = [], False
                for linked in [False, *chained.tolist()]:
                    last = not (linked and last)
                    keep.append(last)
                at = at[np.array(keep)]
            right = after[at]
            far = after[right]
            ids[at], ids[right] = r, -1
            rank[right] = NONE
            rank[at] = NONE
            after[at] = far
            has = far >= 0
            before[far[has]] = at[has]
            lefts = before[at]
            lefts = lefts[lefts >= 0]
            changed = np.concatenate((at[has], lefts))
            if len(changed):
                new = self._pair_rank(ids[changed], ids[after[changed]])
                rank[changed] = new
                some = new != NONE
                if some.any():
                    changed, new = changed[some], new[some]
                    low = new < r
                    if low.any():
                        redo.append(changed[low])
                    for p, x in zip(changed.tolist(), new.tolist()):
                        open_bucket(x).append(p)
        alive = ids >= 0
        counts = np.add.reduceat(alive, starts)
        flat = ids[alive].tolist()
        end = 0
        for i, c in zip(todo, counts.tolist()):
            out[i] = tuple(flat[end : end + c])
            end += c
        if redo:
            for k in np.unique(np.searchsorted(ends, np.concatenate(redo), side="right")).tolist():
                out[todo[k]] = self.encode_one(pieces[todo[k]])
        return out

    # --- texts ----------------------------------------------------------------------
    def encode_texts(self, texts: list[str]) -> Iterator[np.ndarray]:
        """The ids of each text."""
        for a, b in slices([len(t) for t in texts], BATCH_CHARS):
            split = [self.pattern.findall(t) for t in texts[a:b]]
            packed, distinct = self.packed, set().union(*split)
            if len(packed) > MEMO_ENTRIES:  # what this batch needs again stays
                packed = self.packed = {p: packed[p] for p in distinct if p in packed}
            missing = [p for p in distinct if p not in packed]
            for p, ids in zip(missing, self.encode_many([p.encode() for p in missing])):
                packed[p] = array("i", ids).tobytes()
            for pieces in split:
                yield np.frombuffer(b"".join(map(packed.__getitem__, pieces)), dtype=np.int32)
            for p in missing:
                if len(p) > MEMO_CHARS:
                    del packed[p]

    def rest(self) -> None:
        """At a task's end: forget the words, since the worker goes on with other stages (a few kept ones would pin all their memory)."""
        self.packed = {}

    def encode(self, text: str) -> list[int]:
        return next(self.encode_texts([text])).tolist()

    def said(self, ids: list[int]) -> str:
        """Decimal ids joined by one space."""
        return " ".join(map(self.names.__getitem__, ids))

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


_codecs: dict[tuple[str, str], Codec] = {}


def codec_for(rank_file: bytes, pattern: str) -> Codec:
    """A worker's codec, built once for each vocabulary."""
    key = hashlib.sha256(rank_file).hexdigest(), pattern
    if key not in _codecs:
        _codecs[key] = Codec(rank_file, pattern)
    return _codecs[key]


def default_vocabulary() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def vocabulary_bytes(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def encode_documents(
    docs: DataFrame, *, key: str = "doc_id", text: str = "text", rank_path: str | None = None, pattern: str | None = None, keep_ids: bool = True
) -> DataFrame:
    """key, n_tokens, ids (if kept), ids_sha256 and decoded_sha256 of each whole text."""
    small_batches(docs.sparkSession)
    path, default_pattern = default_vocabulary()
    shipped = docs.sparkSession.sparkContext.broadcast(vocabulary_bytes(rank_path or path))  # one file of fixed size
    pattern = pattern or default_pattern
    kind = docs.schema[key].dataType.simpleString()
    schema = f"key {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids
    names = ["n_tokens", "ids_sha256", "decoded_sha256", *(["ids"] if keep_ids else [])]
    types = [pa.int64(), pa.string(), pa.string(), pa.list_(pa.int32())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = codec_for(shipped.value, pattern)
        sha = hashlib.sha256
        for batch in batches:
            for a, b in slices(pc.utf8_length(batch["text"]).to_pylist(), BATCH_CHARS):  # only a slice at a time becomes Python strings
                columns: list[list] = [[] for _ in names]
                for ids in codec.encode_texts(batch["text"].slice(a, b - a).to_pylist()):
                    plain = ids.tolist()
                    for column, value in zip(columns, (len(plain), sha(codec.said(plain).encode()).hexdigest(), sha(codec.decode(plain)).hexdigest(), ids)):
                        column.append(value)
                made = [pa.array(c, type=t) for c, t in zip(columns, types)]
                yield pa.RecordBatch.from_arrays([batch["key"].slice(a, b - a), *made], ["key", *names])
        codec.rest()
        trim_memory()

    return docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(run, schema).withColumnRenamed("key", key)


def decode_documents(encoded: DataFrame, *, key: str = "doc_id", ids: str = "ids", rank_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """key and the decoded bytes of each id list; null lists decode to no bytes."""
    path, default_pattern = default_vocabulary()
    shipped = encoded.sparkSession.sparkContext.broadcast(vocabulary_bytes(rank_path or path))
    pattern = pattern or default_pattern

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec = codec_for(shipped.value, pattern)
        for batch in batches:
            yield pd.DataFrame({"key": batch["key"].array, "decoded": [codec.decode([] if x is None else x) for x in batch["ids"]]})

    kind = encoded.schema[key].dataType.simpleString()
    return encoded.select(F.col(key).alias("key"), F.col(ids).alias("ids")).mapInPandas(run, f"key {kind}, decoded binary").withColumnRenamed("key", key)


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(read_table(spark, sf_dir, "documents"), keep_ids=False)
