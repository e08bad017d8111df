"""Candidates of a containment join without a nested loop: texts meet by hashes that a part and every text around it choose alike.

Of each run of ``w`` windows of ``k`` bytes the one of the least hash is chosen.  A
part of at least k + w - 1 bytes has the choices of a few runs from its first to its last;
whatever text holds the part holds these runs and chooses the same.  So no pair is
missed.  A part brings the choice that the fewest parts have, and where it stands in the
part; texts bring only choices that some part has brought.  Where a text has the choice,
its stretch of the part's length must have the part's hash.  Copies of a part are met once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..staging import staged

#: Window and run lengths by least bytes of a part, longest first; parts below the last meet all texts.
TIERS = ((60, 20, 41), (16, 8, 9), (4, 4, 1))
#: Runs of a part, evenly spaced.
RUNS = 16
#: Places of choices that are compared at once.
PLACES = 1 << 21
#: Pairs that are shipped to the texts.
FEW = 100_000
#: 64-bit words of the bitmap of the parts' choices.
WORDS = 1 << 20
_SLICE = 2_000_000


def windows(texts: list[bytes], k: int, w: int) -> np.ndarray:
    """The hash (63 bits) of the k bytes from each place of all texts joined, and of w places more."""
    data = np.frombuffer(b"".join(texts) + bytes(k + w), dtype=np.uint8).astype(np.uint64)
    factor = np.uint64(0x9E3779B97F4A7C15)
    with np.errstate(over="ignore"):
        span, power, value = 1, factor, (data + np.uint64(1)) * np.uint64(0xC2B2AE3D27D4EB4F)
        value ^= value >> np.uint64(29)
        parts = {1: (value, power)}
        while span * 2 <= k:
            value, power = value[:-span] * power + value[span:], power * power
            span *= 2
            parts[span] = (value, power)
        out, done = parts[span][0], span
        while done < k:
            span = max(x for x in parts if x <= k - done)
            more, power = parts[span]
            out = out[: len(more) - done] * power + more[done : done + len(out)]
            done += span
        out = out ^ (out >> np.uint64(31))
        out *= np.uint64(0xD6E8FEB86659FD93)
        out ^= out >> np.uint64(29)
    return out & np.uint64(2**63 - 1)


def chosen(texts: list[bytes], k: int, w: int, found: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each run that lies within one text: its text, its start in all texts joined, and the least hash of its windows."""
    sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
    least, span = windows(texts, k, w) if found is None else found, 1
    while span * 2 <= w:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < w:
        least = np.minimum(least[: len(least) - (w - span)], least[w - span :])
    ends = np.repeat(np.cumsum(sizes), sizes)
    at = np.flatnonzero(np.arange(len(ends)) + (k + w - 1) <= ends)
    return np.repeat(np.arange(len(texts)), sizes)[at], at, least[at].view(np.int64)


def _parts(texts: list[bytes]) -> Iterator[tuple[int, int]]:
    start, total = 0, 0
    for i, t in enumerate(texts):
        if i > start and total + len(t) > _SLICE:
            yield start, i
            start, total = i, 0
        total += len(t)
    if start < len(texts):
        yield start, len(texts)


def _sums(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a factor, and the sums of scrambled bytes times their powers before each place of all texts joined; both wrap."""
    data = np.frombuffer(b"".join(texts), dtype=np.uint8).astype(np.uint64)
    with np.errstate(over="ignore"):
        powers = np.full(len(data) + 1, 0xC2B2AE3D27D4EB4F, dtype=np.uint64)
        powers[0] = 1
        powers = np.cumprod(powers, dtype=np.uint64)
        data = (data + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        data ^= data >> np.uint64(31)
        sums = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum(data * powers[:-1], dtype=np.uint64, out=sums[1:])
    return powers, sums


def _stretches(texts: list[bytes], asked: pd.DataFrame) -> np.ndarray:
    """Rows of ``asked`` (of, tier, value, at, size, digest; of is a text's number) whose text has a stretch of the size and digest around a window of that value."""
    ends = np.cumsum(np.fromiter(map(len, texts), dtype=np.int64, count=len(texts)))
    starts = np.concatenate(([0], ends[:-1]))
    powers, sums = _sums(texts)
    good = np.zeros(len(asked), dtype=bool)
    for tier in np.unique(asked["tier"]):
        mine = np.flatnonzero(asked["tier"].to_numpy() == tier)
        of, value, at, size, digest = (asked[c].to_numpy(dtype=np.int64)[mine] for c in ("of", "value", "at", "size", "digest"))
        found = windows(texts, *TIERS[tier][1:])[: len(sums) - 1].view(np.int64)
        wanted = np.unique(value)
        place = np.flatnonzero(wanted[np.minimum(np.searchsorted(wanted, found), len(wanted) - 1)] == found)
        # places in order of text and value; a row's places are a slice of them
        text = np.searchsorted(ends, place, side="right")
        code = text * len(wanted) + np.searchsorted(wanted, found[place])
        order = np.argsort(code, kind="stable")
        place, code = place[order], code[order]
        own = of * len(wanted) + np.searchsorted(wanted, value)
        low, high = np.searchsorted(code, own), np.searchsorted(code, own, side="right")
        total = np.cumsum(high - low)
        row = 0
        while row < len(mine):  # as many rows at once as have so many places, one at least
            last = max(row + 1, int(np.searchsorted(total, (total[row - 1] if row else 0) + PLACES, side="right")))
            n = (high - low)[row:last]
            x = np.repeat(np.arange(row, last), n)
            begin = place[np.repeat(low[row:last] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(len(x))] - at[x]
            inside = (begin >= starts[of[x]]) & (begin + size[x] <= ends[of[x]])
            x, begin = x[inside], begin[inside]
            with np.errstate(over="ignore"):
                same = sums[begin + size[x]] - sums[begin] == digest[x].view(np.uint64) * powers[begin]
            good[mine[x[same]]] = True
            row = last
    return good


def containment_candidates(texts: DataFrame, parts: DataFrame, text_key: str, text: str, part_key: str, part: str) -> DataFrame:
    """lk, rk: all pairs where the text can hold the part, and few others; keys are integers. Nulls hold nothing and are held by nothing."""
    pairs, copies = containment_groups(texts, parts, text_key, text, part_key, part)
    return pairs.withColumnRenamed("rk", "first").join(copies, "first").select("lk", "rk")


def containment_groups(texts: DataFrame, parts: DataFrame, text_key: str, text: str, part_key: str, part: str) -> tuple[DataFrame, DataFrame]:
    """The candidates (lk, rk) of each different part, rk being the least key of its copies; and first, rk: the copies of each."""
    given = parts.filter(F.col(part).isNotNull()).select(F.col(part_key).cast("long").alias("rk"), F.col(part).alias("part"))
    given = given.withColumns({"h": F.sha2("part", 256), "size": F.octet_length("part")})

    def brought(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            known = [t.encode() for t in batch["part"]]
            for a, b in _parts(known):
                frame = pd.DataFrame({"h": batch["h"].array[a:b], "rk": batch["rk"].array[a:b], "size": batch["size"].array[a:b], "tier": -1})
                brings: list = [[]] * len(frame)
                sizes, upper = frame["size"].to_numpy(dtype=np.int64), 1 << 62
                ends = np.cumsum(sizes)
                starts = ends - sizes
                for i, (least, k, w) in enumerate(TIERS):
                    mine = np.flatnonzero((sizes >= least) & (sizes < upper))
                    upper = least
                    if not len(mine):
                        continue
                    few = [known[a + x] for x in mine]
                    hashes = windows(few, k, w)
                    of, run, value = chosen(few, k, w, hashes)
                    first = np.flatnonzero(np.diff(of, prepend=-1))
                    begin = np.cumsum(sizes[mine]) - sizes[mine]
                    for x, own, low, n in zip(mine, begin, first, np.diff(first, append=len(of))):
                        at = low + np.unique(np.linspace(0, n - 1, RUNS).astype(np.int64))
                        where = run[at] + np.array([hashes[y : y + w].argmin() for y in run[at]])
                        value_of, one = np.unique(value[at], return_index=True)
                        brings[x] = [{"value": int(v), "at": int(y - own)} for v, y in zip(value_of, where[one])]
                    frame.loc[mine, "tier"] = i
                powers, sums = _sums(known[a:b])
                with np.errstate(over="ignore"):  # the sum from the part's own start: times the inverse power of where it starts
                    frame["digest"] = ((sums[ends] - sums[starts]) * _inverse(powers[starts])).view(np.int64)
                frame["brings"] = brings
                yield frame

    keys = staged(given.mapInPandas(brought, "h string, rk long, size long, tier int, digest long, brings array<struct<value: long, at: long>>"), "parts")
    once = keys.groupBy("h").agg(F.min("rk").alias("first"), F.min_by(F.struct("tier", "size", "digest", "brings"), "rk").alias("one")).select("h", "first", "one.*")
    once = staged(once, "once")
    copies = keys.select("h", "rk").join(once.select("h", "first"), "h").select("first", "rk")
    tiers = [r["tier"] for r in once.select("tier").distinct().collect()]
    slim = texts.filter(F.col(text).isNotNull()).select(F.col(text_key).cast("long").alias("lk"), F.col(text).alias("text"))
    found = slim.select("lk").crossJoin(once.filter("tier = -1").select(F.col("first").alias("rk")))
    wanted = [i for i in tiers if i >= 0]
    if not wanted:  # short parts alone, or none
        return found, copies
    each = once.filter("tier >= 0").select("first", "tier", F.explode("brings").alias("b")).select("first", "tier", "b.value", "b.at")
    counts = each.groupBy("tier", "value").agg(F.count("*").alias("n"))
    rare = each.join(counts, ["tier", "value"]).groupBy("first").agg(F.min_by(F.struct("value", "at"), F.struct("n", "value")).alias("b"))
    rare = staged(once.filter("tier >= 0").select("first", "tier", "size", "digest").join(rare, "first").select(F.col("first").alias("rk"), "tier", "size", "digest", "b.value", "b.at"), "rare")
    bits = rare.select(F.expr(f"cast(value & {64 * WORDS - 1} as int)").alias("bit"))
    words = bits.groupBy(F.shiftright("bit", 6).alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, bit & 63)")).alias("bits")).toPandas()
    marks = np.zeros(WORDS, dtype=np.int64)
    marks[words["at"].to_numpy(dtype=np.int64)] = words["bits"].to_numpy(dtype=np.int64)
    shipped = texts.sparkSession.sparkContext.broadcast(marks.view(np.uint64))

    def met(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        told = shipped.value
        for batch in batches:
            known = [t.encode() for t in batch["text"]]
            rows = batch["lk"].to_numpy(dtype=np.int64)
            for a, b in _parts(known):
                for i in wanted:
                    of, _, value = chosen(known[a:b], *TIERS[i][1:])
                    bit = value & (64 * WORDS - 1)
                    hit = (told[bit >> 6] >> (bit & 63).astype(np.uint64)) & np.uint64(1) == 1
                    yield pd.DataFrame({"lk": rows[a + of[hit]], "tier": i, "value": value[hit]}).drop_duplicates()

    hits = staged(slim.mapInPandas(met, "lk long, tier int, value long"), "met")
    asked = hits.join(rare, ["tier", "value"]).groupBy("lk").agg(F.collect_set(F.struct("tier", "value", "at", "size", "digest", "rk")).alias("asked"))

    def verified(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            known = [t.encode() for t in batch["text"]]
            for a, b in _parts(known):
                rows = [(i, batch["lk"].iat[a + i], *x.values()) for i in range(b - a) for x in batch["asked"].iat[a + i]]
                frame = pd.DataFrame(rows, columns=["of", "lk", "tier", "value", "at", "size", "digest", "rk"])
                yield frame.loc[_stretches(known[a:b], frame), ["lk", "rk"]]

    asked = staged(asked, "asked")
    few = (asked.agg(F.sum(F.size("asked"))).first()[0] or 0) <= FEW
    pairs = staged(slim.join(F.broadcast(asked) if few else asked, "lk").mapInPandas(verified, "lk long, rk long"), "candidates")
    return found.unionByName(pairs) if -1 in tiers else pairs, copies


def _inverse(odd: np.ndarray) -> np.ndarray:
    """Of odd numbers, modulo 2**64."""
    out = odd.copy()
    for _ in range(6):
        out *= np.uint64(2) - odd * out
    return out
