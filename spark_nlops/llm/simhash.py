"""SimHash near-duplicates with pivot distance tables.

Fingerprints that differ in at most two of 64 bits agree in at least six of
eight bytes.  Each *distinct* fingerprint is therefore listed under its 28
six-byte masks; a bucket holds at most 2^16 distinct fingerprints whatever the
data, and copies have been folded away before.  Within a bucket the Hamming
distances to fixed reference fingerprints (pivots) are tabled: by the triangle
inequality a pair whose distances to any pivot differ by more than the limit
cannot link and is discarded; what survives is verified by XOR and bit count.
Verified links are reduced to a spanning forest of the bucket, so no group emits
all its pairs, and components are found by star contraction.

Defined results: null and empty texts have no words and fingerprint zero, linked
like any other; fewer words than a shingle form one shingle; copies share a
fingerprint; a null key is fingerprinted, has no component of its own and can't
stand for others; an empty table gives an empty table; other columns of the
input are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import Stage, read_table, slices, small_batches, text_or_empty, trim_memory
from .graph import connected_components

SEED, MAX_BITS = 42, 2
#: Reference fingerprints: 24 fixed draws of a seeded generator.
PIVOTS = np.random.default_rng(20240101).integers(0, 2**64, 24, dtype=np.uint64)
_LINES = 16_384


def fingerprint(text: str, shingle: int = 3) -> int:
    """Bitwise majority of the XXH64 values of all shingles, repeats included."""
    words = text.encode().lower().split()
    n = len(words)
    if not n:
        return 0
    joined = b" ".join(words)
    if n <= shingle:
        hashes = [xxh64_intdigest(joined, SEED)]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=n) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))[: n - shingle + 1]
        hashes = [xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts.tolist(), ends[shingle - 1 :].tolist())]
    return majority(np.array(hashes, dtype="<u8"))


def majority(values: np.ndarray) -> int:
    """Bits that are set in over half of the values."""
    ones = np.zeros(64, dtype=np.int64)
    for i in range(0, len(values), _LINES):
        ones += np.unpackbits(values[i : i + _LINES].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(ones * 2 > len(values), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, *, key: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """key and fingerprint (long, two's complement) of each whole text."""
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            values = np.array([fingerprint(t, shingle) for t in batch["text"]], dtype=np.uint64)
            yield pd.DataFrame({"key": batch["key"].array, "fp": values.view(np.int64)})

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInPandas(run, f"key {kind}, fp long").withColumnRenamed("key", key)


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        up = parent[parent]
        if np.array_equal(up, parent):
            return parent
        parent = up


def linked_forest(group: np.ndarray, values: np.ndarray, max_bits: int = MAX_BITS, pivots: np.ndarray = PIVOTS) -> np.ndarray:
    """For entries sorted by group: the index of each one's root among those linked to it inside its group."""
    n = len(values)
    table = np.bitwise_count(values[:, None] ^ pivots[None, :]).astype(np.int16)
    order = np.lexsort((table[:, 0], group))
    group, values, table = group[order], values[order], table[order]
    parent = np.arange(n)
    rows = np.arange(n - 1)
    step = 1
    while len(rows := rows[rows + step < n]):
        near = (group[rows] == group[rows + step]) & (table[rows + step, 0] - table[rows, 0] <= max_bits)
        rows = rows[near]  # sorted by the first pivot: once too far, all later ones are
        left, right = rows, rows + step
        apart = parent[left] != parent[right]
        left, right = left[apart], right[apart]
        kept = np.abs(table[left] - table[right]).max(axis=1) <= max_bits if len(left) else np.zeros(0, bool)
        left, right = left[kept], right[kept]
        linked = np.bitwise_count(values[left] ^ values[right]) <= max_bits
        if linked.any():
            for a, b in zip(left[linked].tolist(), right[linked].tolist()):
                while parent[a] != a:
                    a = parent[a]
                while parent[b] != b:
                    b = parent[b]
                if a != b:
                    parent[max(a, b)] = min(a, b)
            parent = _roots(parent)
        step += 1
    out = np.empty(n, dtype=np.int64)
    out[order] = order[parent]
    return out


def fingerprint_links(distinct: DataFrame, *, max_bits: int = MAX_BITS) -> DataFrame:
    """Links (a, b) between the representatives of distinct fingerprints; columns rep, fp. Each bucket gives a spanning forest."""
    if not 0 <= max_bits <= 2:
        raise ValueError("the byte masks find links of at most two bits")
    masks = []
    for left_out in combinations(range(8), 2):
        mask = 2**64 - 1
        for byte in left_out:
            mask &= ~(0xFF << (8 * byte))
        masks.append(mask - 2**64 if mask >= 2**63 else mask)
    buckets = (
        distinct.select(
            F.struct("rep", "fp").alias("item"),
            F.explode(F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(m))) for i, m in enumerate(masks)])).alias("bucket"),
        )
        .groupBy("bucket")
        .agg(F.collect_list("item").alias("items"))
        .filter(F.size("items") > 1)
        .select(F.col("items.rep").alias("reps"), F.col("items.fp").alias("fps"))
    )

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sizes = [len(x) for x in batch["fps"]]
            for a, b in slices(sizes, 200_000):
                reps = np.concatenate(batch["reps"].iloc[a:b].to_list()).astype(np.int64)
                fps = np.concatenate(batch["fps"].iloc[a:b].to_list()).astype(np.int64).view(np.uint64)
                root = linked_forest(np.repeat(np.arange(b - a), sizes[a:b]), fps, max_bits)
                other = np.flatnonzero(root != np.arange(len(root)))
                yield pd.DataFrame({"a": reps[other], "b": reps[root[other]]})

    return buckets.mapInPandas(run, "a long, b long").filter("a <> b").distinct()


def near_duplicates(docs: DataFrame, *, key: str = "doc_id", text: str = "text", shingle: int = 3, max_bits: int = MAX_BITS, stage: Stage | None = None) -> DataFrame:
    """key, fp and component (smallest key reachable over links) for every row. Keys are integers."""
    stage = stage or Stage(docs.sparkSession, "simhash")
    marked = stage.keep(fingerprints(docs.withColumn(key, F.col(key).cast("long")), key=key, text=text, shingle=shingle), "fps")
    distinct = marked.filter(F.col(key).isNotNull()).groupBy("fp").agg(F.min(key).alias("rep"))
    links = stage.keep(fingerprint_links(distinct, max_bits=max_bits), "links")
    parts = connected_components(links, stage)
    named = distinct.join(parts.select(F.col("node").alias("rep"), "component"), "rep", "left").select(
        "fp", F.coalesce("component", "rep").alias("component")
    )
    return marked.join(named, "fp", "left").select(key, "fp", F.when(F.col(key).isNotNull(), F.col("component")).alias("component"))


def hex_fingerprint(name: str = "fp"):
    return F.lpad(F.lower(F.hex(F.col(name))), 16, "0")


def op3_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", hex_fingerprint().alias("fingerprint"), F.col("component").alias("component_id"))


# --- near-duplicates by shingle similarity ---------------------------------------------
#: Least shingles of a text by which candidates meet; two texts of similarity s share none with probability (1 - s)^SKETCH.
SKETCH = 8
#: Members of a bucket up to which all its pairs are listed; larger buckets first compare each member with their leaders, then what is still apart by prefixes.
ALL_PAIRS = 32
#: Members of a block when a large bucket is compared block against block.
BLOCK = 1024
#: 64-bit words of a set's parity bitmap.
PARITY = 8
#: 64-bit words of the bitmap that tells which texts are compared.
MARKS = 1 << 20
#: Texts whose shingles are counted to tell common shingles from rare ones, and the number of common ones told to all tasks.
COUNTED, COMMON = 4_000, 200_000


def shingle_set(text: str, shingle: int) -> np.ndarray:
    """The distinct shingle hashes in order."""
    words = text.encode().lower().split()
    n = len(words)
    if not n:
        return np.zeros(0, dtype=np.uint64)
    joined = b" ".join(words)
    if n <= shingle:
        values = np.array([xxh64_intdigest(joined, SEED)], dtype="<u8")
    else:
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=n) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))[: n - shingle + 1]
        values = np.array([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts.tolist(), ends[shingle - 1 :].tolist())], dtype="<u8")
    return np.unique(values)


def parity(grams: np.ndarray) -> np.ndarray:
    """Bitmap that every member of a set of 32-bit hashes flips a bit of: two bitmaps differ in no more bits than their sets in members."""
    bits = np.bincount(grams & np.uint32(64 * PARITY - 1), minlength=64 * PARITY) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little").view("<i8")


def _grams(values: np.ndarray) -> np.ndarray:
    """The set's members as sorted 32-bit hashes."""
    return np.unique((values >> np.uint64(32)).astype("<u4"))


def _sets(docs: DataFrame, key: str, text: str, shingle: int) -> DataFrame:
    """doc, whole (hash of the set), n, sketch and parity of each text; the sets themselves are not kept."""
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for a, b in slices(batch["text"].map(len).tolist(), 4_000_000):
                rows = []
                for t in batch["text"].iloc[a:b]:
                    values = shingle_set(t, shingle)
                    grams = _grams(values)
                    rows.append((int(np.uint64(xxh64_intdigest(values.tobytes(), SEED)).view(np.int64)), len(grams), values[:SKETCH].view(np.int64), parity(grams)))
                yield pd.DataFrame({"doc": batch["doc"].array[a:b]} | {c: [r[i] for r in rows] for i, c in enumerate(["whole", "n", "sketch", "parity"])})
        trim_memory()

    rows = docs.select(F.col(key).cast("long").alias("doc"), text_or_empty(text).alias("text"))
    return rows.mapInPandas(run, "doc long, whole long, n int, sketch array<long>, parity array<long>")


def _bit(name: str):
    return F.pmod(F.xxhash64(F.lit(9), name), F.lit(64 * MARKS))


def _compared(docs: DataFrame, key: str, text: str, shingle: int, wanted: DataFrame) -> DataFrame:
    """rep, n and grams (sorted 32-bit shingle hashes) of at least the wanted keys (column rep).

    Texts stay where they are: the keys are told as a bitmap of one size, whose
    collisions let some more texts through.
    """
    words = wanted.select(_bit("rep").alias("bit")).groupBy(F.shiftright("bit", 6).alias("at")).agg(F.bit_or(F.expr("shiftleft(1L, cast(bit & 63 as int))")).alias("bits")).toPandas()
    marks = np.zeros(MARKS, dtype=np.int64)
    marks[words["at"].to_numpy(dtype=np.int64)] = words["bits"].to_numpy(dtype=np.int64)
    shipped = docs.sparkSession.sparkContext.broadcast(marks.view(np.uint64))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        told = shipped.value
        for batch in batches:
            bit = batch["bit"].to_numpy(dtype=np.int64)
            batch = batch[(told[bit >> 6] >> (bit & 63).astype(np.uint64)) & np.uint64(1) == 1]
            for a, b in slices(batch["text"].map(len).tolist(), 4_000_000):
                grams = [_grams(shingle_set(t, shingle)) for t in batch["text"].iloc[a:b]]
                yield pd.DataFrame({"rep": batch["rep"].array[a:b], "n": [len(g) for g in grams], "grams": [g.tobytes() for g in grams]})
        trim_memory()

    rows = docs.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("rep"), text_or_empty(text).alias("text"))
    return rows.withColumn("bit", _bit("rep")).mapInPandas(run, "rep long, n int, grams binary")


def _may_be_near(x, y, similarity: float):
    """Whether the parity bitmaps leave room for the similarity: members in one set only are at most (1 - s) / (1 + s) of both lengths, and every bit that differs needs one."""
    differ = sum((F.bit_count(x["parity"][i].bitwiseXOR(y["parity"][i])) for i in range(1, PARITY)), F.bit_count(x["parity"][0].bitwiseXOR(y["parity"][0])))
    return differ <= F.lit((1 - similarity) / (1 + similarity)) * (x["n"] + y["n"]) + 1e-6


def _candidates(sets: DataFrame, similarity: float, stage: Stage) -> tuple[DataFrame, DataFrame]:
    """Pairs (a, b) of representatives that meet in a small sketch bucket, or as member and leader of a large one, and whose parity bitmaps leave room for the similarity; and the members (value, rep) of large buckets."""
    member = F.struct("rep", "n", "parity")
    keys = stage.keep(sets.select(F.explode("sketch").alias("value"), "rep", "n", "parity"), "keys")
    counts = keys.groupBy("value").agg(F.count("*").alias("m")).filter("m > 1")
    met = stage.keep(keys.join(counts, "value"), "met")
    # a text's weight: how often its sketch is met elsewhere; the text that copies were made from has the largest
    weights = met.groupBy("rep").agg(F.sum(F.log2("m")).alias("weight"))
    members = stage.keep(met.filter(F.col("m") > ALL_PAIRS).select("value", "rep"), "large")
    large = met.filter(F.col("m") > ALL_PAIRS).join(weights, "rep")
    leaders = large.groupBy("value").agg(
        F.max_by(member, F.struct("weight", "rep")).alias("l1"), F.min_by(member, F.struct("rep")).alias("l2"), F.max_by(member, F.struct("n", "rep")).alias("l3")
    )
    led = large.join(leaders, "value").select(member.alias("x"), F.explode(F.array("l1", "l2", "l3")).alias("y"))
    few = met.filter(F.col("m") <= ALL_PAIRS).groupBy("value").agg(F.sort_array(F.collect_list(member)).alias("items"))
    few = few.select(F.posexplode("items").alias("at", "x"), "items").select("x", F.explode(F.slice("items", F.col("at") + 2, F.size("items"))).alias("y"))
    pairs = led.unionByName(few).filter("x.rep <> y.rep").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).filter(
        (F.least("x.n", "y.n") >= F.lit(similarity) * F.greatest("x.n", "y.n"))
    )
    near = pairs.filter(_may_be_near(F.col("x"), F.col("y"), similarity))
    return near.select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b")).distinct(), members


def _verified(pairs: DataFrame, grams: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose sets have at least the similarity."""
    ends = pairs.select("a", "b", F.explode(F.array("a", "b")).alias("rep"))
    held = ends.join(grams.select("rep", "grams"), "rep").groupBy("a", "b").agg(F.min("grams").alias("g1"), F.max("grams").alias("g2"))

    def verify(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            keep = []
            for g1, g2 in zip(batch["g1"], batch["g2"]):
                x, y = np.frombuffer(g1, dtype="<u4"), np.frombuffer(g2, dtype="<u4")
                both = np.concatenate((x, y))
                both.sort()
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(shared >= similarity * (len(both) - shared))
            yield batch.loc[np.array(keep, dtype=bool), ["a", "b"]]
        trim_memory()

    return held.mapInPandas(verify, "a long, b long")


def _settled(pairs: DataFrame, known: DataFrame, grams: DataFrame, n: int, similarity: float, stage: Stage, name: str) -> DataFrame:
    """Links (a, b) that give the components of all pairs (a, b) of the similarity, beside the known links.

    A pair's sets are written to it twice over, so pairs are verified in parts of
    about ``n``, the number of sets, whose shuffles are freed one after the other.
    What earlier parts have joined is not verified again.
    """
    size = pairs.count()
    parts = max(1, -(-size // max(n, 1)))
    if parts == 1:
        return stage.keep(_verified(pairs, grams, similarity), name)
    found = None
    for i in range(parts):
        todo = pairs.filter(F.pmod(F.xxhash64(F.lit(7), "a", "b"), F.lit(parts)) == i)
        if found is not None:
            joined = stage.keep(connected_components(found.unionByName(known), stage), f"{name}_joined{i}")
            for end in ("a", "b"):
                todo = todo.join(joined.select(F.col("node").alias(end), F.col("component").alias(f"c{end}")), end, "left").withColumn(f"c{end}", F.coalesce(f"c{end}", end))
            todo = todo.filter("ca <> cb").select("a", "b")
        links = stage.keep(_verified(todo, grams, similarity), f"{name}{i}")
        if i:
            stage.drop(f"{name}_joined{i}")
        found = links if found is None else found.unionByName(links)
        stage.release()
    return found


def _common_shingles(texts: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """The commonest shingles of a bounded sample in order, and their counts. They only decide which order is cheap: prefixes are complete in any order."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for a, b in slices(batch["grams"].map(len).tolist(), 8_000_000):
                gram, count = np.unique(np.frombuffer(b"".join(batch["grams"].iloc[a:b]), dtype="<u4"), return_counts=True)
                yield pd.DataFrame({"gram": gram.view(np.int32), "n": count})

    drawn = texts.filter(F.pmod(F.xxhash64(F.lit(5), "rep"), F.lit(1_000_000)) < F.lit(min(1.0, COUNTED / max(n, 1)) * 1_000_000))
    counts = drawn.select("grams").mapInPandas(run, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n")).filter("n > 1")
    best = counts.orderBy(F.desc("n"), "gram").limit(COMMON).toPandas()
    gram, count = best["gram"].to_numpy(dtype=np.int32).view(np.uint32), best["n"].to_numpy(dtype=np.int64)
    order = np.argsort(gram)
    return gram[order], count[order]


def _prefixes(texts: DataFrame, similarity: float, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """token, at, rep, component and n for the rarest shingles of each text: sets of the similarity share one of these at least, whatever the order."""
    shipped = texts.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known, counts = shipped.value
        for batch in batches:
            tokens = []
            for grams in batch["grams"]:
                g = np.frombuffer(grams, dtype="<u4")
                seen = np.zeros(len(g), dtype=np.int64)
                if len(known):
                    place = np.minimum(np.searchsorted(known, g), len(known) - 1)
                    seen = np.where(known[place] == g, counts[place], 0)
                length = len(g) - int(np.ceil(similarity * len(g) - 1e-9)) + 1 if len(g) else 0
                tokens.append(g[np.lexsort((g, seen))[:length]].view(np.int32))
            yield pd.DataFrame({"rep": batch["rep"].array, "component": batch["component"].array, "n": batch["n"].array, "tokens": tokens})

    rows = texts.select("rep", "component", "n", "grams").mapInPandas(run, "rep long, component long, n int, tokens array<int>")
    return rows.select(F.posexplode("tokens").alias("at", "token"), "rep", "component", "n")


def _across(keys: DataFrame, similarity: float, stage: Stage) -> DataFrame:
    """Pairs (a, b) of different components that share a prefix token and whose lengths and places in the order leave room for the similarity."""
    counts = keys.groupBy("token").agg(F.count("*").alias("m"), F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo < hi")
    met = stage.keep(keys.join(counts.select("token", "m"), "token"), "across_met")
    share = similarity / (1 + similarity)
    member = F.struct("rep", "component", "n", "at")
    few = met.filter(F.col("m") <= ALL_PAIRS).groupBy("token").agg(F.sort_array(F.collect_list(member)).alias("items"))
    few = few.select(F.posexplode("items").alias("place", "x"), "items").select("x", F.explode(F.slice("items", F.col("place") + 2, F.size("items"))).alias("y"))
    few = few.filter(
        (F.col("x.component") != F.col("y.component"))
        & (F.least("x.n", "y.n") >= F.lit(similarity) * F.greatest("x.n", "y.n") - 1e-6)
        # the first shared token has no shared ones before it, so what follows it bounds the overlap
        & (F.least(F.col("x.n") - F.col("x.at"), F.col("y.n") - F.col("y.at")) >= F.lit(share) * (F.col("x.n") + F.col("y.n")) - 1e-6)
    ).select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"))
    blocks = F.ceil(F.col("m") / BLOCK).cast("int")
    dealt = met.filter(F.col("m") > ALL_PAIRS).withColumn("own", F.pmod(F.xxhash64("rep"), blocks).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    cells = (
        dealt.groupBy("token", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))
        .agg(F.collect_list(F.struct("rep", "component", "n", "at", "own")).alias("items"))
        .select("i", "j", *[F.col(f"items.{c}").alias(c) for c in ("rep", "component", "n", "at", "own")])
    )

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for row in batch.itertuples(index=False):
                rep, component, n, at, own = (np.asarray(v, dtype=np.int64) for v in (row.rep, row.component, row.n, row.at, row.own))
                left, right = np.flatnonzero(own == row.i), np.flatnonzero(own == row.j)
                for k in range(0, len(left), 256):
                    x, y = left[k : k + 256, None], right[None, :]
                    near = component[x] != component[y]
                    near &= np.minimum(n[x], n[y]) >= similarity * np.maximum(n[x], n[y]) - 1e-6
                    near &= np.minimum(n[x] - at[x], n[y] - at[y]) >= share * (n[x] + n[y]) - 1e-6
                    if row.i == row.j:
                        near &= rep[x] < rep[y]
                    a, b = np.nonzero(near)
                    if len(a):
                        a, b = rep[left[k + a]], rep[right[b]]
                        yield pd.DataFrame({"a": np.minimum(a, b), "b": np.maximum(a, b)})

    return few.unionByName(cells.mapInPandas(compare, "a long, b long")).distinct()


def _links_across(grams: DataFrame, parities: DataFrame, large: DataFrame, parts: DataFrame, similarity: float, stage: Stage) -> DataFrame | None:
    """Verified links (a, b) between members of large buckets that the links so far leave in different components; None if there is nothing to compare."""
    names = parts.select(F.col("node").alias("rep"), F.col("component").alias("known"))
    named = large.join(names, "rep", "left").select("value", "rep", F.coalesce("known", "rep").alias("component"))
    apart = named.groupBy("value").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo < hi").select("value")
    members = stage.keep(named.join(apart, "value", "left_semi").select("rep", "component").distinct(), "members")
    n = members.count()
    if not n:
        return None
    texts = stage.keep(members.join(grams, "rep"), "texts")
    keys = stage.keep(_prefixes(texts, similarity, _common_shingles(texts, n)), "tokens")
    pairs = stage.keep(_across(keys, similarity, stage), "across")
    for name in ("tokens", "across_met"):
        stage.drop(name)
    stage.release()
    held = parities.join(members.select("rep"), "rep", "left_semi").select("rep", F.struct("n", "parity").alias("set"))
    for end in ("a", "b"):
        pairs = pairs.join(held.select(F.col("rep").alias(end), F.col("set").alias(f"s{end}")), end)
    near = stage.keep(pairs.filter(_may_be_near(F.col("sa"), F.col("sb"), similarity)).select("a", "b"), "across_near")
    stage.drop("across")
    known = members.filter("rep <> component").select(F.col("rep").alias("a"), F.col("component").alias("b"))
    links = _settled(near, known, texts, n, similarity, stage, "across_links")
    stage.drop("texts")
    return links


def similar_documents(docs: DataFrame, *, key: str = "doc_id", text: str = "text", shingle: int = 5, similarity: float = 0.8, stage: Stage | None = None) -> DataFrame:
    """key and component of every row: components of texts whose shingle sets have at least the given Jaccard similarity.

    Texts with the same set are folded.  Candidates share one of their least
    shingles; bitmaps of the sets' parities discard candidates that provably differ
    in more members than such pairs do; the sets themselves verify the rest.  Buckets of
    more than ``ALL_PAIRS`` different texts first compare every member with three
    leaders (the text that is met most often, the first, and the longest).  Members
    that these links leave in different components are then compared by prefixes:
    with rare shingles first, sets of the similarity share a token of their prefixes,
    large tokens are compared block against block, and the sets verify what is left.
    Pairs within a component are not compared, since they can't change the result.
    """
    stage = stage or Stage(docs.sparkSession, "similar")
    marked = stage.keep(_sets(docs, key, text, shingle), "sets")
    folded = marked.filter("doc IS NOT NULL").groupBy("whole").agg(F.min("doc").alias("rep"))
    sets = marked.join(folded, (marked["doc"] == folded["rep"]) & (marked["whole"] == folded["whole"]), "left_semi").dropDuplicates(["doc", "whole"]).withColumnRenamed("doc", "rep")
    sets = sets.select("rep", "n", "sketch", "parity")
    pairs, large = _candidates(sets, similarity, stage)
    pairs = stage.keep(pairs, "pairs")
    stage.drop("keys")
    stage.drop("met")
    stage.release()
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("rep")).unionByName(large.select("rep"))
    grams = stage.keep(_compared(docs, key, text, shingle, wanted), "grams")
    links = _settled(pairs, pairs.limit(0), grams, grams.count(), similarity, stage, "links")
    parts = stage.keep(connected_components(links, stage), "parts")
    stage.release()
    more = _links_across(grams, sets, large, parts, similarity, stage)
    stage.drop("grams")
    if more is not None:
        parts = connected_components(links.unionByName(more), stage)
    named = folded.join(parts.select(F.col("node").alias("rep"), "component"), "rep", "left").select("whole", F.coalesce("component", "rep").alias("component"))
    out = marked.select("doc", "whole").join(named, "whole", "left")
    return out.select(F.col("doc").alias(key), F.when(F.col("doc").isNotNull(), F.col("component")).alias("component"))


def duplicate_groups(docs: DataFrame, *, key: str = "doc_id", text: str = "text", similarity: float = 0.8) -> DataFrame:
    """key and component of the rows that are in a group of several keys: linked by fingerprints of three words at two bits, or by sets of five words at the similarity."""
    slim = docs.select(F.col(key).cast("long").alias("key"), F.col(text).alias("text"))
    stage = Stage(docs.sparkSession, "groups")
    inner = Stage(docs.sparkSession, "inner")  # its tables go as soon as the groups are written
    near = stage.keep(near_duplicates(slim, key="key", stage=inner).filter("component <> key").select("key", "component"), "near")
    inner.clear()
    inner.release()
    similar = stage.keep(similar_documents(slim, key="key", similarity=similarity, stage=inner).filter("component <> key").select("key", "component"), "similar")
    inner.clear()
    inner.release()
    links = near.unionByName(similar).select(F.col("key").alias("a"), F.col("component").alias("b")).distinct()
    return connected_components(links, stage).select(F.col("node").alias(key), "component")
