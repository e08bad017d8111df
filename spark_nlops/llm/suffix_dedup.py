"""Exact repeated-substring removal with threshold-bounded BWT interval expansion.

A byte is removed if a ``length``-byte string that covers it also starts
anywhere else in the table.  The work is split so that no task sees the corpus:

1. *Anchors.*  Each window of ``length`` bytes picks the least of its 64-byte
   hashes (leftmost on ties).  Equal windows pick the same anchor at the same
   offset, so windows can only be equal within one anchor value.  Consecutive
   windows with one anchor form a piece; one row for each piece leaves the scan,
   about one for 70 bytes.
2. *Counts.*  Anchors that occur once are gone after a partial aggregation.
   Where all pieces of an anchor have one digest, every window of them repeats.
3. *Suffix intervals.*  The distinct pieces of the other anchors are packed, an
   anchor always whole, into bounded texts.  Of each text the Burrows-Wheeler
   transform is built and intervals are extended backward breadth-first: level l
   sets the borders whose common prefix is l, and after level ``length - 1`` the
   borders never set are those with a common prefix of ``length`` or more.
4. *Crowds.*  An anchor with more than ``CROWD`` distinct pieces (a passage that
   very many documents share, in different surroundings) is cut into blocks of
   neighbouring windows.  All windows of a block hold its core, and equal windows
   lie in blocks of equal cores, so blocks are grouped by core, folded, and
   expanded like pieces; groups that are still crowded are cut into narrower
   blocks, down to single windows.  So no anchor meets in one task.

Pieces of one anchor are called equal by a 64-bit digest of all their bytes beside
the 64-bit anchor; everything else is compared byte by byte in the intervals.

Defined results: null texts count as empty; texts shorter than ``length`` keep
all bytes; repeated rows are copies of each other; null keys are judged like any
others; an empty table gives an empty table; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stage, free_name, read_table, slices, small_batches, text_or_empty, trim_memory

LENGTH, GRAM = 200, 64
#: Distinct pieces that are still expanded together; where an anchor has more, windows of a block, wide blocks first.
CROWD = 512
WIDTHS = (32, 4, 1)
#: Bytes scanned together, and bytes of one Burrows-Wheeler text.
SCAN_BYTES, TEXT_BYTES = 1 << 18, 250_000
#: A piece's place is start * PLACE + windows.
PLACE = 1024
_RNG = np.random.default_rng(77)
_BYTE_HASH = _RNG.integers(0, 2**64, 256, dtype=np.uint64)
_FACTORS = [np.uint64(int(x) | 1) for x in _RNG.integers(2**60, 2**63, 10)]
_LOW = np.uint64((1 << 20) - 1)


def _doubled(h: np.ndarray, span: int, step: int) -> np.ndarray:
    """Hashes of twice the span from hashes of the span."""
    out = h[:-span] * _FACTORS[step]
    out += h[span:]
    out ^= out >> np.uint64(29)
    out *= _FACTORS[9]
    return out


def _hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the 64 and of the 128 bytes from each position."""
    h, span, step = _BYTE_HASH[data], 1, 0
    while span < GRAM:
        h, span, step = _doubled(h, span, step), span * 2, step + 1
    return h, _doubled(h, span, step)


def _mixed(*parts: np.ndarray) -> np.ndarray:
    out = np.zeros(len(parts[0]), dtype=np.uint64)
    for i, part in enumerate(parts):
        out = (out ^ part.astype(np.uint64)) * _FACTORS[i]
        out ^= out >> np.uint64(31)
    return out


def pieces_of(texts: list[bytes], length: int = LENGTH) -> dict[str, np.ndarray]:
    """For texts scanned together: owner, start, windows, anchor and digest of each piece."""
    if not texts:
        return {}
    sizes = np.array([len(t) for t in texts], dtype=np.int64)
    data = np.frombuffer(b"".join(texts), dtype=np.uint8)
    n = len(data)
    if n < length or sizes.max() < length:
        return {}
    h64, h128 = _hashes(data)
    width = length - GRAM + 1
    keyed = (h64 & ~_LOW) | np.arange(len(h64), dtype=np.uint64)
    least, span = keyed, 1
    while span * 2 <= width:
        least, span = np.minimum(least[:-span], least[span:]), span * 2
    if span < width:
        least = np.minimum(least[: len(least) - (width - span)], least[width - span :])
    anchor = (least & _LOW).astype(np.int64)  # one for each window of the joined texts
    ends = np.cumsum(sizes)
    owner = np.repeat(np.arange(len(texts)), sizes)
    valid = owner[: n - length + 1] == owner[length - 1 :]
    cut = np.empty(len(anchor), dtype=bool)
    cut[0] = True
    cut[1:] = (anchor[1:] != anchor[:-1]) | (valid[1:] != valid[:-1]) | (owner[1 : len(anchor)] != owner[: len(anchor) - 1])
    at = np.flatnonzero(cut)
    windows = np.diff(np.append(at, len(anchor)))
    at, windows = at[valid[at]], windows[valid[at]]
    whole = windows + (length - 1)
    digest = _mixed(h128[at], h128[at + (whole - 128) // 2], h128[at + whole - 128], whole)
    own = owner[at]
    return {
        "owner": own,
        "start": at - (ends - sizes)[own],
        "windows": windows,
        "anchor": h64[anchor[at]].view(np.int64),
        "digest": digest.view(np.int64),
    }


# --- Burrows-Wheeler interval expansion ------------------------------------------------
def _rotation_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Positions sorted by the next ``depth`` symbols (or more) of the cyclic text, then by position."""
    key = np.zeros(len(text), dtype=np.int64)
    for i in range(6):  # six symbols of at most ten bits
        key = (key << 10) | np.roll(text, -i)
    span = 6
    while True:
        order = np.argsort(key, kind="stable")
        ordered = key[order]
        fresh = np.concatenate(([0], np.cumsum(ordered[1:] != ordered[:-1])))
        if span >= depth or fresh[-1] == len(text) - 1:
            return order
        rank = np.empty(len(text), dtype=np.int64)
        rank[order] = fresh
        key = (rank << 32) | np.roll(rank, -span)
        span *= 2


def repeated_positions(text: np.ndarray, length: int) -> np.ndarray:
    """Whether the next ``length`` symbols also start elsewhere; symbol 0 separates and never takes part.

    Only positions with no separator among these symbols have a meaning.  The text
    starts with a separator.  A border of the sorted suffixes that level l reaches
    first has a common prefix of l symbols; levels stop at ``length - 1``.
    """
    n = len(text)
    order = _rotation_order(text, length + 1).astype(np.int32)
    last = text[order - 1]  # the transform: the symbol before each suffix
    back = np.empty(n, dtype=np.int32)
    back[np.argsort(last, kind="stable")] = np.arange(n)  # row of the suffix one symbol longer
    firsts = np.zeros(n + 1, dtype=bool)
    firsts[np.concatenate(([0], np.cumsum(np.bincount(text))))] = True  # rows where the first symbol changes
    is_text = last != 0
    known = np.zeros(n + 1, dtype=bool)
    known[[0, n]] = True
    low, high = np.array([0]), np.array([n])
    owner = np.full(n, -1, dtype=np.int32)
    for level in range(length):
        size = high - low
        total = int(size.sum())
        if not total:
            break
        base = np.repeat(low - (np.cumsum(size) - size), size)
        rows = np.arange(total) + base
        which = np.repeat(np.arange(len(low)), size)
        used = is_text[rows] | (level == 0)  # a separator may end a string, so that borders beside one are set too
        rows, which = back[rows[used]], which[used]
        owner[rows] = which
        rows = np.flatnonzero(owner >= 0) if total * 8 > n else np.sort(rows)
        if not len(rows):
            break
        of = owner[rows]
        starts = np.empty(len(rows), dtype=bool)
        starts[0] = True
        starts[1:] = (rows[1:] != rows[:-1] + 1) | (of[1:] != of[:-1]) | firsts[rows[1:]]
        begin = np.flatnonzero(starts)
        end = np.append(begin[1:], len(rows)) - 1
        owner[rows] = -1
        low, high = rows[begin], rows[end] + 1
        new = ~known[high]
        low, high = low[new], high[new]
        known[high] = True
    shared = ~known[:n]  # row i and row i - 1 have at least ``length`` symbols in common
    out = np.zeros(n, dtype=bool)
    at = np.flatnonzero(shared)
    out[order[at]] = True
    out[order[at - 1]] = True
    return out


def repeated_windows(pieces: list[bytes], copies: np.ndarray, length: int = LENGTH) -> list[np.ndarray]:
    """For pieces that hold their anchors' groups whole: which windows of each start elsewhere too."""
    sizes = np.array([len(p) for p in pieces], dtype=np.int64)
    text = np.frombuffer(b"\0" + b"\0".join(pieces), dtype=np.uint8).astype(np.int64)
    starts = 1 + np.cumsum(sizes + 1) - (sizes + 1)
    text += 1
    text[0] = 0
    text[starts[1:] - 1] = 0
    found = repeated_positions(text, length)
    return [
        np.ones(s - length + 1, dtype=bool) if c > 1 else found[a : a + s - length + 1] for a, s, c in zip(starts.tolist(), sizes.tolist(), copies.tolist())
    ]


def _runs(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    edge = np.diff(np.concatenate(([0], mask.astype(np.int8), [0])))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


# --- the distributed job -------------------------------------------------------------
def _scan_pieces(docs: DataFrame, length: int) -> DataFrame:
    """doc, mark, place (start and windows in one number), anchor and digest; docs has doc, mark and text."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for x, y in slices(batch["text"].map(len).tolist(), 4_000_000):
                texts = [t.encode() for t in batch["text"].iloc[x:y]]
                rows, parts, offsets = [], [], []
                for i, t in enumerate(texts):
                    if len(t) < length:
                        continue
                    # long texts overlap by one byte less than a window, so each window is in one part
                    for a in range(0, max(1, len(t) - length + 1), SCAN_BYTES):
                        rows.append(x + i)
                        offsets.append(a)
                        parts.append(t[a : a + SCAN_BYTES + length - 1])
                rows, offsets = np.array(rows, dtype=np.int64), np.array(offsets, dtype=np.int64)
                found = []
                for a, b in slices([len(p) for p in parts], SCAN_BYTES):
                    if got := pieces_of(parts[a:b], length):
                        own = got.pop("owner") + a
                        got["start"] = got["start"] + offsets[own]
                        found.append(got | {"row": rows[own]})
                if found:
                    got = {k: np.concatenate([f[k] for f in found]) for k in found[0]}
                    row = got.pop("row")
                    got["place"] = got.pop("start") * PLACE + got.pop("windows")
                    yield pd.DataFrame({"doc": batch["doc"].array[row], "mark": batch["mark"].to_numpy()[row]} | got)[["doc", "mark", "place", "anchor", "digest"]]
        trim_memory()

    kind = docs.schema["doc"].dataType.simpleString()
    return docs.mapInPandas(run, f"doc {kind}, mark long, place long, anchor long, digest long")


def _cut_pieces(wanted: DataFrame, docs: DataFrame, length: int) -> DataFrame:
    """The bytes of representative pieces: anchor, digest, copies, piece."""
    lists = wanted.groupBy("doc", "mark").agg(F.collect_list(F.struct("place", "anchor", "digest", "copies")).alias("want"))
    joined = docs.join(lists, docs["doc"].eqNullSafe(lists["doc"]) & (docs["mark"] == lists["mark"])).select(docs["text"], "want")
    joined = joined.select(F.encode("text", "UTF-8").alias("bytes"), "want")
    pieces = F.expr(f"transform(want, w -> struct(w.anchor, w.digest, w.copies, substring(bytes, cast(w.place div {PLACE} as int) + 1, cast(w.place % {PLACE} as int) + {length - 1}) AS piece))")
    return joined.select(pieces.alias("pieces")).select(F.explode("pieces").alias("p")).select("p.*")


def _runs_frame(rows: pd.DataFrame, length: int) -> pd.DataFrame:
    """group, digest and the runs of repeated windows of the pieces that have any; groups are whole."""
    rows = rows.drop_duplicates(["group", "digest"])  # of rows that are there twice
    masks = repeated_windows(rows["piece"].tolist(), rows["copies"].to_numpy(), length)
    keep = np.flatnonzero([m.any() for m in masks])
    spans = [_runs(masks[i]) for i in keep]
    # object columns, also where nothing repeats
    low, high = (pd.Series([s[end] for s in spans], dtype=object) for end in (0, 1))
    return pd.DataFrame({"group": rows["group"].to_numpy()[keep], "digest": rows["digest"].to_numpy()[keep], "low": low, "high": high})


def _expand(pieces: DataFrame, length: int) -> DataFrame:
    """group, digest and the runs of repeated windows (low, high arrays) of each piece that has any."""

    def solved(rows: pd.DataFrame, last: bool) -> Iterator[pd.DataFrame | int]:
        """Frames of whole groups, in texts of bounded size; then the row from which on groups may go on."""
        groups = rows["group"].to_numpy()
        borders = np.append(0, np.flatnonzero(groups[1:] != groups[:-1]) + 1)
        if last:
            borders = np.append(borders, len(rows))
        sums = np.add.reduceat(rows["piece"].map(len).to_numpy(), borders[:-1]) if len(borders) > 1 else np.zeros(0, int)
        for a, b in slices(sums.tolist(), TEXT_BYTES):
            yield _runs_frame(rows.iloc[borders[a] : borders[b]], length)
        yield int(borders[-1])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        waiting, size = [], 0
        for batch in batches:
            waiting.append(batch)
            size += int(batch["piece"].map(len).sum())
            if size < TEXT_BYTES:
                continue
            rows = pd.concat(waiting, ignore_index=True)
            *frames, rest = solved(rows, False)
            yield from frames
            waiting = [rows.iloc[rest:]]
            size = int(waiting[0]["piece"].map(len).sum())
        if waiting and len(rows := pd.concat(waiting, ignore_index=True)):
            *frames, _ = solved(rows, True)
            yield from frames
        trim_memory()

    spread = pieces.select("group", "digest", "copies", "piece").repartition("group").sortWithinPartitions("group")
    return spread.mapInPandas(run, "group long, digest long, low array<int>, high array<int>")


def block_keys(piece: bytes, anchor: int, width: int, length: int = LENGTH) -> dict[str, np.ndarray]:
    """Blocks of ``width`` windows of a piece, cut at fixed distances from the anchor: first window, windows, hash of the core and digest.

    All windows of a block, whole or cut off by the piece's end, hold the block's core; so equal windows have equal cores.
    """
    h64, h128 = _hashes(np.frombuffer(piece, dtype=np.uint8))
    n = len(piece) - length + 1
    lead = int(np.flatnonzero(h64.view(np.int64) == anchor)[0])  # windows take the leftmost place of the least hash
    block = (lead - np.arange(n)) // width
    low = np.flatnonzero(np.concatenate(([True], block[1:] != block[:-1])))
    high = np.append(low[1:], n) - 1
    number = block[low]
    core, rest = lead - number * width, length - width + 1 - GRAM  # the core's start, and what follows its first gram
    whole = high - low + length
    return {
        "low": low,
        "windows": high - low + 1,
        "group": _mixed(*[h64[core + rest * i // 3] for i in range(4)], number).view(np.int64),
        "digest": _mixed(h128[low], h128[low + (whole - 128) // 2], h128[low + whole - 128], lead - low, lead - high).view(np.int64),
    }


def _blocks(crowd: DataFrame, width: int, length: int) -> DataFrame:
    """The blocks of crowded pieces: owner (group and digest of the piece), low, windows, group, digest, anchor, copies."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for a, b in slices(batch["piece"].map(len).tolist(), SCAN_BYTES):
                found = []
                for group, digest, copies, anchor, piece in batch.iloc[a:b][["group", "digest", "copies", "anchor", "piece"]].itertuples(index=False):
                    found.append(pd.DataFrame({"owner": group, "owner_digest": digest} | block_keys(piece, anchor, width, length) | {"anchor": anchor, "copies": copies}))
                yield pd.concat(found, ignore_index=True)
        trim_memory()

    return crowd.mapInPandas(run, "owner long, owner_digest long, low int, windows int, group long, digest long, anchor long, copies long")


def _solve(pieces: DataFrame, length: int, stage: Stage, widths: tuple[int, ...] = WIDTHS) -> DataFrame:
    """group, digest and runs of repeated windows (low, high arrays) of pieces: a stage table of group, digest (different within a group), copies, anchor, piece. A piece may have several rows."""
    crowds = pieces.groupBy("group").agg(F.count("*").alias("k")).filter(F.col("k") > CROWD).select("group")
    if not widths or not (crowds := stage.keep(crowds, f"crowds{len(widths)}")).limit(1).count():
        return _expand(pieces, length)
    few = _expand(pieces.join(crowds, "group", "left_anti"), length)
    crowd = pieces.join(crowds, "group", "left_semi")
    blocks = stage.keep(_blocks(crowd, widths[0], length), f"blocks{len(widths)}")
    kinds = blocks.groupBy("group", "digest").agg(
        F.sum("copies").alias("copies"), F.min("windows").alias("windows"), F.min("anchor").alias("anchor"), F.min(F.struct("owner", "owner_digest", "low")).alias("at")
    )
    # a core that occurs once holds no repeated window, and all windows of several blocks that are one kind repeat
    sizes = kinds.groupBy("group").agg(F.count("*").alias("k"), F.sum("copies").alias("c")).filter("c > 1").select("group", "k")
    dealt = stage.keep(kinds.join(sizes, "group"), f"kinds{len(widths)}")
    alike = dealt.filter("k = 1").select("group", "digest", F.array(F.lit(0)).alias("low"), F.array("windows").alias("high"))
    mixed = dealt.filter("k > 1").select("group", "digest", "copies", "windows", F.col("at.owner").alias("owner"), F.col("at.owner_digest").alias("owner_digest"), F.col("at.low").alias("low"))
    whole = crowd.select(F.col("group").alias("owner"), F.col("digest").alias("owner_digest"), "anchor", "piece")
    part = F.substring("piece", F.col("low") + 1, F.col("windows") + (length - 1))
    cut = stage.keep(mixed.join(whole, ["owner", "owner_digest"]).select("group", "digest", "copies", "anchor", part.alias("piece")), f"cut{len(widths)}")
    found = alike.unionByName(_solve(cut, length, stage, widths[1:]))
    back = blocks.select("group", "digest", "owner", "owner_digest", F.col("low").alias("from")).join(found, ["group", "digest"])
    moved = back.select(
        F.col("owner").alias("group"), F.col("owner_digest").alias("digest"), *[F.transform(c, lambda x: x + F.col("from")).alias(c) for c in ("low", "high")]
    )
    return few.unionByName(moved)


def repeated_spans(docs: DataFrame, *, length: int = LENGTH, stage: Stage | None = None) -> DataFrame:
    """doc, mark, lows and highs (byte offsets of spans, unmerged) of the rows with repeats; docs has doc, mark, text."""
    if not 2 * GRAM <= length <= 2 * GRAM + 128:
        raise ValueError(f"length must be from {2 * GRAM} to {2 * GRAM + 128}")
    small_batches(docs.sparkSession)
    stage = stage or Stage(docs.sparkSession, "suffix")
    pieces = stage.keep(_scan_pieces(docs, length), "pieces")
    seen = pieces.groupBy("anchor").agg(F.count("*").alias("n"), F.min("digest").alias("d1"), F.max("digest").alias("d2")).filter("n > 1")
    seen = seen.select("anchor", (F.col("d1") == F.col("d2")).alias("alike"))
    # written first, so that both sides of the join are plain exchanges, of which adaptive execution can split a hot anchor
    seen = stage.keep(seen, "seen")
    stage.release()
    shared = stage.keep(pieces.join(seen, "anchor").select(*pieces.columns, "alike"), "shared")
    stage.drop("pieces")
    stage.drop("seen")
    stage.release()
    mixed = shared.filter(~F.col("alike"))
    kinds = mixed.groupBy("anchor", "digest").agg(F.count("*").alias("copies"), F.min(F.struct("doc", "mark", "place")).alias("at"))
    wanted = kinds.select("anchor", "digest", "copies", "at.*")
    cut = stage.keep(_cut_pieces(wanted, docs, length), "cut")
    stage.release()
    solved = stage.keep(_solve(cut.withColumn("group", F.col("anchor")), length, stage), "solved")
    stage.drop("cut")
    start, windows = F.expr(f"cast(place div {PLACE} as int)"), F.expr(f"cast(place % {PLACE} as int)")
    plain = shared.filter("alike").select("doc", "mark", F.array(F.struct(start.alias("low"), (start + windows + length - 1).alias("high"))).alias("spans"))
    partly = mixed.join(solved.withColumnRenamed("group", "anchor"), ["anchor", "digest"]).select(
        "doc",
        "mark",
        F.zip_with("low", "high", lambda a, b: F.struct((start + a).alias("low"), (start + b + length - 1).alias("high"))).alias("spans"),
    )
    spans = plain.unionByName(partly).groupBy("doc", "mark").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    return spans.select("doc", "mark", F.col("spans.low").alias("lows"), F.col("spans.high").alias("highs"))  # plain numbers for Python


def merged(lows, highs) -> list[tuple[int, int]]:
    """Spans as maximal disjoint runs; None stands for no spans."""
    if lows is None or not len(lows):
        return []
    lows, highs = np.asarray(lows, dtype=np.int64), np.asarray(highs, dtype=np.int64)
    order = np.argsort(lows, kind="stable")
    lows, highs = lows[order], np.maximum.accumulate(highs[order])
    first = np.flatnonzero(np.concatenate(([True], lows[1:] > highs[:-1])))
    return list(zip(lows[first].tolist(), highs[np.append(first[1:], len(lows)) - 1].tolist()))


def whole_characters(data: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans shrunk to whole UTF-8 characters."""
    out = []
    for low, high in spans:
        while low < high and data[low] & 0xC0 == 0x80:
            low += 1
        while high > low and high < len(data) and data[high] & 0xC0 == 0x80:
            high -= 1
        if low < high:
            out.append((low, high))
    return out


def _kept(data: bytes, spans: list[tuple[int, int]]) -> bytes:
    at, parts = 0, []
    for low, high in spans:
        parts.append(data[at:low])
        at = high
    return b"".join([*parts, data[at:]])


def keyed(docs: DataFrame, key: str, text: str) -> DataFrame:
    return docs.select(F.col(key).alias("doc"), text_or_empty(text).alias("text")).withColumn("mark", F.xxhash64("text"))


def remove_repeats(docs: DataFrame, *, key: str = "doc_id", text: str = "text", length: int = LENGTH, digest_only: bool = False) -> DataFrame:
    """key, n_bytes, n_removed, n_spans, kept_sha256 and, unless digest_only, kept (whole characters) and spans of every row."""
    rows = keyed(docs, key, text)
    found = repeated_spans(rows, length=length)
    extra = "" if digest_only else ", kept string, spans array<struct<low:int,high:int>>"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for t, lows, highs in zip(batch["text"], batch["lows"], batch["highs"]):
                data = t.encode()
                spans = merged(lows, highs)
                bare = _kept(data, spans)
                row = (len(data), len(data) - len(bare), len(spans), hashlib.sha256(bare).hexdigest())
                if not digest_only:
                    row += (_kept(data, whole_characters(data, spans)).decode(), [{"low": a, "high": b} for a, b in spans])
                out.append(row)
            names = ["n_bytes", "n_removed", "n_spans", "kept_sha256", *([] if digest_only else ["kept", "spans"])]
            yield pd.DataFrame({"doc": batch["doc"].array} | {c: [r[i] for r in out] for i, c in enumerate(names)})

    both = rows.join(found, rows["doc"].eqNullSafe(found["doc"]) & (rows["mark"] == found["mark"]), "left").select(rows["doc"], "text", "lows", "highs")
    kind = docs.schema[key].dataType.simpleString()
    return both.mapInPandas(run, f"doc {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string{extra}").withColumnRenamed("doc", key)


def without_repeats(docs: DataFrame, *, key: str = "doc_id", text: str = "text", length: int = LENGTH) -> DataFrame:
    """All rows and columns, the text without its repeated bytes (whole characters only)."""
    found = repeated_spans(keyed(docs, key, text), length=length)
    own, doc, mark, lows, highs = (free_name(docs, f"nlops_{x}") for x in ("own", "doc", "mark", "lows", "highs"))
    found = found.select(F.col("doc").alias(doc), F.col("mark").alias(mark), F.col("lows").alias(lows), F.col("highs").alias(highs))

    @F.pandas_udf("string")
    def cut(texts: pd.Series, lows: pd.Series, highs: pd.Series) -> pd.Series:
        out = []
        for t, low, high in zip(texts, lows, highs):
            if low is None:
                out.append(t)
                continue
            data = t.encode()
            out.append(_kept(data, whole_characters(data, merged(low, high))).decode())
        return pd.Series(out, dtype=object)

    marked = docs.withColumn(own, F.xxhash64(text_or_empty(text)))
    both = marked.join(found, F.col(key).eqNullSafe(F.col(doc)) & (F.col(own) == F.col(mark)), "left")
    return both.withColumn(text, F.when(F.col(lows).isNull(), F.col(text)).otherwise(cut(text_or_empty(text), F.col(lows), F.col(highs)))).select(*docs.columns)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(read_table(spark, sf_dir, "documents").select("doc_id", "text"), digest_only=True)


OP5_SQL = """
WITH d AS (
  SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents
), starts AS (
  SELECT doc_id, i, md5_number(substr(h, 2 * i + 1, 400)) AS k FROM (SELECT doc_id, h, unnest(range(0, length(h) // 2 - 199)) AS i FROM d)
), often AS (
  SELECT k, count(*) AS n FROM starts GROUP BY k HAVING count(*) > 1
), counted AS (
  SELECT doc_id, i, n FROM starts JOIN often USING (k)
), marked AS (
  SELECT doc_id, i, CASE WHEN i - lag(i) OVER (PARTITION BY doc_id ORDER BY i) <= 200 THEN 0 ELSE 1 END AS fresh FROM counted WHERE n > 1
), numbered AS (
  SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i ROWS UNBOUNDED PRECEDING) AS no FROM marked
), spans AS (
  SELECT doc_id, min(i) AS low, max(i) + 200 AS high FROM numbered GROUP BY doc_id, no
), cut AS (
  SELECT s.doc_id, low, high, substr(h, 2 * coalesce(lag(high) OVER (PARTITION BY s.doc_id ORDER BY low), 0) + 1, 2 * (low - coalesce(lag(high) OVER (PARTITION BY s.doc_id ORDER BY low), 0))) AS part
  FROM spans s JOIN d ON d.doc_id = s.doc_id
), gone AS (
  SELECT doc_id, sum(high - low) AS n_removed, count(*) AS n_spans, string_agg(part, '' ORDER BY low) AS front, max(high) AS last FROM cut GROUP BY doc_id
)
SELECT d.doc_id, (length(h) // 2)::BIGINT AS n_bytes, coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_spans, 0)::BIGINT AS n_spans,
  sha256(unhex(coalesce(front, '') || substr(h, 2 * coalesce(last, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN gone ON gone.doc_id = d.doc_id
"""
