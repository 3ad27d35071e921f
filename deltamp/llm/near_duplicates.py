"""Near-duplicate groups: MinHash bands, sequential Bayesian pruning, exact verification.

1. A text becomes its set of hashed word shingles. Texts whose whole word sequences are equal (so that their sets are)
   are collapsed to the row of the smallest id, by a cryptographic digest of the words, so copies never meet in pairs.
2. The rest get ``HASHES`` min-hashes in ``BANDS`` bands. Rows that share a band are candidates.
3. A candidate pair's one-byte signatures are compared batch by batch. With m of n equal, the similarity
   has a Beta posterior; the pair is dropped as soon as the posterior probability of reaching the
   threshold is below ``MISS``. Survivors are verified on their full shingle sets.
4. Rounds against hubs come first: each row tries the hub that it shares most buckets with, one pair a row. They go on
   while they link a tenth of what they try. Linked rows need no test among themselves any more.
5. All that is left is searched bucket by bucket: the members of a bucket go in blocks, the test runs on all pairs of two
   blocks at once and gives a spanning forest of the pairs that survive, so no table ever holds a pair for each
   two members. The members of the largest linked component of a bucket are not compared with each other.
6. Rows that the forest connects get their full sets, in blocks again, and give the links among them, a forest as well.

At similarity 0.8 two rows share no band with probability (1 - 0.8**6)**40, about 5e-6, and a pair is pruned
wrongly with less than ``len(least_equal(80)) * MISS`` (``wrongly_pruned`` gives the exact figure).

Defined cases: words are runs of other than ASCII white space, A-Z in lower case; a text with fewer words than a shingle is one
shingle; a null, empty or blank text has none and is linked with nothing; an empty table gives no rows; other columns
are not carried on. Rows of one id, and rows without an id, are documents of their own, which only a link joins: they
are compared under numbers, the component has the smallest id of its rows (null if none has one), and of each
component one row is kept, that of the smallest id, then of the smallest hash of the text.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textbuf
from .common import BROADCAST_BYTES, Scratch, cut, dealt, hot_keys, read, semi_by_id
from .components import components
from .grouped import enter, whole_groups

ROWS, BANDS = 6, 40
HASHES = ROWS * BANDS
BATCH, MISS = 40, 1e-6
#: Rows of a block when signatures are compared, shingles of a block when sets are, pairs that are tested at once.
BLOCK_ROWS, BLOCK_ITEMS, PAIRS = 512, 100_000, 1 << 18

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BLANK = np.zeros(256, bool)
_BLANK[[0x20, 9, 10, 11, 12, 13]] = True


def shingles(raw: np.ndarray, at: np.ndarray, words: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's shingles."""
    low = _LOWER[raw]
    starts, ends, first = textbuf.runs(~_BLANK[low], at)
    h = textbuf.span_hashes(textbuf.letters(256)[low], starts, ends)
    joined = h.copy()
    step = np.uint64(0x9E3779B97F4A7C15)
    for j in range(1, words):
        joined = joined[: max(0, len(h) - j)] * step
        joined = textbuf.mix(joined + h[j:])
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= words:
            s = np.sort(joined[a : b - words + 1])
            out.append(s[np.concatenate(([True], s[1:] != s[:-1]))])
        elif b > a:
            one = h[a : a + 1] ^ np.uint64(0x5851F42D4C957F2D)
            for k in range(a + 1, b):
                one = textbuf.mix(one * step + h[k : k + 1])
            out.append(one)
        else:
            out.append(h[:0])
    return out


@lru_cache(maxsize=1)
def _permutations() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    r = np.random.default_rng(2024)
    a = (r.integers(0, 1 << 31, HASHES, dtype=np.int64) * 2 + 1).astype(np.uint32)[:, None]
    b = r.integers(0, 1 << 32, HASHES, dtype=np.int64).astype(np.uint32)[:, None]
    return a, b, r.integers(1, 1 << 63, ROWS, dtype=np.int64).astype(np.uint64) | np.uint64(1), r.integers(1, 1 << 63, BANDS, dtype=np.int64).astype(np.uint64)


def minima(s: np.ndarray) -> np.ndarray:
    a, b, _, _ = _permutations()
    x, low = (s >> np.uint64(32)).astype(np.uint32), np.full(HASHES, 0xFFFFFFFF, np.uint32)
    for k in range(0, len(x), 2048):
        np.minimum(low, (x[None, k : k + 2048] * a + b).min(1), out=low)
    return low


def plain_words(raw: np.ndarray, at: np.ndarray) -> list[bytes]:
    """A digest of each text's words in lower case with one blank between; two texts share it only if their words are the same."""
    low = _LOWER[raw]
    inside = ~_BLANK[low]
    follows = np.zeros(len(low), bool)
    follows[:-1] = inside[1:]
    keep = inside | (~inside & follows)  # of a run of blanks the last one, if a word comes after it in the text
    last = at[1:][at[1:] > at[:-1]] - 1
    keep[last] &= inside[last]
    low[~inside] = 0x20
    ends = np.concatenate(([0], np.cumsum(keep)))[at]
    flat = low[keep].tobytes()
    return [blake2b(flat[a:b].lstrip(b" "), digest_size=16).digest() for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]


def sketch(docs: DataFrame, words: int, text: str = "text", key: str = "doc_id") -> DataFrame:
    """id, n, digest of the words, band hashes and one-byte signature of each row."""

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("near duplicates")
        _, _, inner, outer = _permutations()
        for batch in batches:
            raw, at, _ = textbuf.utf8(batch.column(1))
            for i, j in textbuf.groups(at):
                part, ends = raw[at[i] : at[j]], at[i : j + 1] - at[i]
                sets = shingles(part, ends, words)
                low = np.stack([minima(s) for s in sets])
                n = np.array([len(s) for s in sets])
                bands = textbuf.mix((low.reshape(-1, BANDS, ROWS).astype(np.uint64) * inner).sum(2, dtype=np.uint64) + outer).view(np.int64)
                some = n > 0
                stops = np.concatenate(([0], np.cumsum(some * BANDS)))
                signature = pa.FixedSizeBinaryArray.from_buffers(pa.binary(HASHES), j - i, [None, pa.py_buffer((low & 255).astype(np.uint8).tobytes())]).cast(pa.binary())
                columns = [batch.column(0)[i:j], pa.array(n, pa.int64()), pa.array(plain_words(part, ends), pa.binary()), pa.ListArray.from_arrays(pa.array(stops, pa.int32()), pa.array(bands[some].ravel())), signature]
                yield pa.RecordBatch.from_arrays(columns, ["id", "n", "same", "bands", "sig"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInArrow(sketched, f"id {kind}, n long, same binary, bands array<long>, sig binary")


def sets(docs: DataFrame, words: int, text: str = "text", key: str = "doc_id") -> DataFrame:
    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, at, _ = textbuf.utf8(batch.column(1))
            for i, j in textbuf.groups(at):
                found = shingles(raw[at[i] : at[j]], at[i : j + 1] - at[i], words)
                ends = np.concatenate(([0], np.cumsum([len(s) for s in found])))
                yield pa.RecordBatch.from_arrays([batch.column(0)[i:j], pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(found).view(np.int64)))], ["id", "items"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInArrow(listed, f"id {kind}, items array<long>")


@lru_cache(maxsize=4)
def least_equal(percent: int) -> tuple[int, ...]:
    """For 1, 2, .. batches the least number of equal bytes at which the threshold is still likely enough.

    With a uniform prior, P(similarity >= t | m of n equal) = P(Binomial(n + 1, t) <= m); a byte is also
    equal by chance once in 256.
    """
    t = percent / 100 + (1 - percent / 100) / 256
    out = []
    for n in range(BATCH, HASHES + 1, BATCH):
        total, m = 0.0, -1
        while total < MISS:
            m += 1
            total += math.comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
        out.append(m)
    return tuple(out)


def wrongly_pruned(similarity: float, percent: int) -> float:
    """Probability that the test drops a pair of this similarity: the equal bytes are followed from batch to batch."""
    p = similarity + (1 - similarity) / 256
    alive, gone = {0: 1.0}, 0.0
    for least in least_equal(percent):
        after: dict[int, float] = {}
        for m, w in alive.items():
            for x in range(BATCH + 1):
                after[m + x] = after.get(m + x, 0.0) + w * math.comb(BATCH, x) * p**x * (1 - p) ** (BATCH - x)
        gone += sum(w for m, w in after.items() if m < least)
        alive = {m: w for m, w in after.items() if m >= least}
    return gone


def survivors(left: np.ndarray, right: np.ndarray, i: np.ndarray, j: np.ndarray, percent: int) -> np.ndarray:
    """Which of the pairs (i of ``left``, j of ``right``) of signatures the sequential test doesn't drop."""
    alive, equal = np.arange(len(i)), np.zeros(len(i), int)
    for k, least in enumerate(least_equal(percent)):
        part = slice(k * BATCH, (k + 1) * BATCH)
        equal = equal + (left[i[alive], part] == right[j[alive], part]).sum(1)
        alive, equal = alive[equal >= least], equal[equal >= least]
    return alive


def _near(x: str, y: str, percent: int):
    """The sizes alone don't rule the pair out."""
    return F.least(x, y) * 100 >= F.greatest(x, y) * percent


def verify(pairs: DataFrame, full: DataFrame, percent: int, scratch: Scratch) -> DataFrame:
    """Pairs (a, b), one for each b, that pass the test on signatures and reach the threshold on full sets; a hub may have any number."""
    pairs = scratch.keep(pairs)
    kind, total = pairs.schema["a"].dataType.simpleString(), pairs.count()
    hot = hot_keys(pairs.groupBy("a").agg(F.count("*").alias("rows")), "a", total)

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            left, right = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint8).reshape(-1, HASHES) for k in (2, 3))
            every = np.arange(len(left))
            at = pa.array(survivors(left, right, every, every, percent))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(1).take(at)], ["a", "b"])

    side = lambda name, column: full.select(F.col("id").alias(name), F.col(column).alias(f"{column}_{name}"))
    both = dealt(pairs.join(side("b", "sig"), "b"), side("a", "sig"), "a", hot, "b")
    left = scratch.keep(both.select("a", "b", "sig_a", "sig_b").mapInArrow(kept, f"a {kind}, b {kind}"))
    both = dealt(left.join(side("b", "items"), "b"), side("a", "items"), "a", hot, "b")
    common = F.size(F.array_intersect("items_a", "items_b"))
    sized = both.select("a", "b", common.alias("c"), (F.size("items_a") + F.size("items_b")).alias("t"))
    found = scratch.keep(sized.where(100 * F.col("c") >= percent * (F.col("t") - F.col("c"))).select("a", "b"))
    scratch.drop(pairs, left)
    return found


def in_blocks(rows: DataFrame, group: str, weight: str, size: int, scratch: Scratch) -> DataFrame:
    """Rows (group, id, root, weight, ..) of the groups with several roots, once for each pair of blocks (x, y) that is to be compared.

    The rows of a group's heaviest root form blocks of their own, which are compared with all others but not among
    themselves. A block weighs about ``size``; ``first`` tells that a row comes from block x.
    """
    by_root = rows.groupBy(group, "root").agg(F.sum(weight).alias("w"))
    info = by_root.groupBy(group).agg(F.sum("w").alias("all"), F.max(F.struct("w", "root")).alias("top"), F.count("*").alias("roots")).where("roots > 1")
    whole = F.col("all") <= size
    info = scratch.keep(info.select(group, F.when(whole, 1).otherwise(F.ceil((F.col("all") - F.col("top.w")) / size)).cast("long").alias("n"), F.when(whole, 0).otherwise(F.ceil(F.col("top.w") / size)).cast("long").alias("m"), F.col("top.root").alias("most"), F.col("all").alias("rows")))
    total = info.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    placed = dealt(rows, info.drop("rows"), group, hot_keys(info.select(group, "rows"), group, total), "id")
    h = F.xxhash64("id", F.lit(3))
    placed = placed.withColumn("own", F.when((F.col("m") > 0) & (F.col("root") == F.col("most")), F.col("n") + F.pmod(h, F.greatest("m", F.lit(1)))).otherwise(F.pmod(h, F.col("n"))))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.when(F.col("own") >= F.col("n"), F.col("n")).otherwise(F.col("n") + F.col("m")) - 1)))
    placed = placed.withColumns({"x": F.least("own", "other"), "y": F.greatest("own", "other"), "first": F.col("own") <= F.col("other")})
    return placed.drop("n", "m", "most", "own", "other")


def _pair_ranges(starts: np.ndarray, n: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs (i < j) of rows within groups that begin at ``starts``, at most about ``PAIRS`` at once."""
    ends = np.repeat(np.append(starts[1:], n), np.diff(np.append(starts, n)))
    later = ends - np.arange(n) - 1
    total = np.concatenate(([0], np.cumsum(later)))
    a = 0
    while a < n:
        b = max(a + 1, int(np.searchsorted(total, total[a] + PAIRS, "right")) - 1)
        i = np.repeat(np.arange(a, b), later[a:b])
        yield i, i + 1 + np.arange(len(i)) - np.repeat(total[a:b] - total[a], later[a:b])
        a = b


def _labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest row of each row's component."""
    label = np.arange(n)
    while len(a):
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        label = label[label]
        if (before == label).all():
            break
    return label


def forest(blocks: DataFrame, group: str, percent: int, exact: bool) -> DataFrame:
    """Edges (a, b) of a spanning forest of the pairs within ``in_blocks`` rows that pass the test on signatures, or are links by their sets.

    Pairs of one root are not compared. Memory is bounded by the size of two blocks.
    """
    names = [group, "x", "y", "id", "root", "n", "first", "sig", *(["items"] if exact else [])]

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t, starts in whole_groups(batches):
            x, y, ids, root, n, first = (t.column(c).to_numpy() for c in names[1:7])
            sig = np.frombuffer(b"".join(t.column("sig").to_pylist()), np.uint8).reshape(-1, HASHES)
            lefts, rights = [], []
            for i, j in _pair_ranges(starts, len(ids)):
                open_ = (root[i] != root[j]) & ((x[i] == y[i]) | (first[i] != first[j])) & (np.minimum(n[i], n[j]) * 100 >= np.maximum(n[i], n[j]) * percent)
                i, j = i[open_], j[open_]
                alive = survivors(sig, sig, i, j, percent)
                lefts.append(i[alive])
                rights.append(j[alive])
            i, j = np.concatenate(lefts), np.concatenate(rights)
            if exact and len(i):
                c = _common(t.column("items").combine_chunks(), i, j)
                link = 100 * c >= percent * (n[i] + n[j] - c)
                i, j = i[link], j[link]
            label = _labels(len(ids), i, j)
            away = np.flatnonzero(label != np.arange(len(ids)))
            yield pa.RecordBatch.from_arrays([pa.array(ids[label[away]]), pa.array(ids[away])], ["a", "b"])

    kind = blocks.schema["id"].dataType.simpleString()
    rows = blocks.select(*names).repartition(group, "x", "y").sortWithinPartitions(group, "x", "y")
    return rows.mapInArrow(found, f"a {kind}, b {kind}")


def _common(items: pa.ListArray | pa.ChunkedArray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of the sets of rows i with those of rows j; ``i`` is sorted."""
    if isinstance(items, pa.ChunkedArray):
        items = pa.concat_arrays(items.chunks)
    at = items.offsets.to_numpy().astype(np.int64)
    at, (_, place) = at - at[0], np.unique(items.flatten().to_numpy(), return_inverse=True)
    seen, out = np.zeros(place.max(initial=0) + 1, bool), np.empty(len(i), np.int64)
    cuts = np.concatenate(([0], np.flatnonzero(i[1:] != i[:-1]) + 1, [len(i)]))
    for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
        mine = place[at[i[a]] : at[i[a] + 1]]
        seen[mine] = True
        size = at[j[a:b] + 1] - at[j[a:b]]
        first = np.cumsum(size) - size
        hits = seen[place[np.arange(size.sum()) + np.repeat(at[j[a:b]] - first, size)]]
        out[a:b] = np.add.reduceat(hits, first, dtype=np.int64)
        seen[mine] = False
    return out


def unique(docs: DataFrame, key: str = "doc_id") -> bool:
    """Whether every row has an id of its own."""
    return docs.groupBy(F.col(key).alias("_id")).agg(F.count("*").alias("_n")).where("_n > 1 OR _id IS NULL").isEmpty()


def numbered(docs: DataFrame) -> DataFrame:
    """``docs`` with a number for each row in ``_row``, kept, so that it stays the same."""
    return cut(docs.withColumn("_row", F.monotonically_increasing_id()))


def by_row(rows: DataFrame, words: int = 5, percent: int = 80, text: str = "text", key: str = "doc_id") -> DataFrame:
    """_row, doc_id, n_shingles, component_id and kept of every row of ``numbered`` rows, whatever their ids are."""
    found = cut(_grouped(rows, words, percent, text, "_row").select(F.col("doc_id").alias("_row"), "n_shingles", "component_id"))
    named = rows.select("_row", F.col(key).alias("doc_id"), F.xxhash64(text).alias("_h"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id"), F.col("_h"), F.col("_row"))).alias("first")
    shared = found.groupBy("component_id").agg(F.count("*").alias("rows")).where("rows > 1").select("component_id")
    best = cut(found.join(shared, "component_id").join(named, "_row").groupBy("component_id").agg(first))
    side = F.broadcast(best) if best.count() * 64 <= BROADCAST_BYTES else best
    placed = found.join(named.drop("_h"), "_row").join(side, "component_id", "left")
    lone = F.col("first").isNull()
    return placed.select("_row", "doc_id", "n_shingles", F.when(lone, F.col("doc_id")).otherwise(F.col("first.doc_id")).alias("component_id"), (lone | (F.col("first._row") == F.col("_row"))).alias("kept"))


def near_duplicates(docs: DataFrame, words: int = 5, percent: int = 80, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, n_shingles, component_id (smallest id reachable) and kept of every row."""
    if unique(docs, key):
        return _grouped(docs, words, percent, text, key)
    return by_row(numbered(docs.select(key, text)), words, percent, text, key).drop("_row")


def _grouped(docs: DataFrame, words: int, percent: int, text: str, key: str) -> DataFrame:
    """The result for rows whose ids are not null and all different."""
    spark = docs.sparkSession
    s = Scratch(spark, "near-duplicates")
    known = s.keep(sketch(docs, words, text, key))
    live, total = known.where("n > 0"), known.count()
    groups = s.keep(live.groupBy("same").agg(F.min("id").alias("first"), F.count("*").alias("rows")).where("rows > 1"))
    hot = hot_keys(groups.select("same", "rows"), "same", total)
    copies = s.keep(dealt(live.select("id", "same"), groups.select("same", "first"), "same", hot, "id").where("id <> first").select("id", "first"))
    gone = copies.select("id")
    alone = live.join(F.broadcast(gone) if copies.count() * 16 <= BROADCAST_BYTES else gone, "id", "left_anti")
    rows = alone.select("id", "n", F.explode("bands").alias("band"))
    shared = s.keep(rows.groupBy("band").agg(F.min(F.struct("id", "n")).alias("hub"), F.count("*").alias("rows")).where("rows > 1"))
    total = shared.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    hot = hot_keys(shared.select("band", "rows"), "band", total)
    members = s.keep(dealt(rows, shared.select("band", "hub"), "band", hot, "id"))
    wanted = s.keep(members.select("id").distinct())
    listed = sets(semi_by_id(docs.select(key, text), wanted.withColumnRenamed("id", key), key, wanted.count()), words, text, key)
    full = s.keep(known.select("id", "n", "sig").join(listed, "id"))
    roots, edges = _searched(members, full, hot, percent, s)
    s.drop(members, wanted, full, shared, edges)
    # copies go where their first one goes
    hot = hot_keys(groups.select("first", "rows"), "first", known.count())
    moved = dealt(copies, roots.withColumnRenamed("node", "first"), "first", hot, "id", "left").select("id", F.coalesce("root", "first").alias("root"))
    place = s.keep(roots.select(F.col("node").alias("id"), "root").union(moved))
    s.drop(copies, groups)
    out = known.select("id", "n").join(place, "id", "left").select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("root", "id").alias("component_id"))
    return out.withColumn("kept", F.col("doc_id") == F.col("component_id"))


def _searched(members: DataFrame, full: DataFrame, hot: DataFrame | None, percent: int, s: Scratch) -> tuple[DataFrame, DataFrame]:
    """(node, root) of all links between ``members`` (band, id, n, hub) of buckets, and the links; ``hot``: the hot buckets."""
    kind = members.schema["id"].dataType.simpleString()
    edges = s.keep(members.sparkSession.createDataFrame([], f"a {kind}, b {kind}"))
    roots, placed, turn = s.keep(edges.toDF("node", "root")), None, 0

    def linked(more: DataFrame) -> None:
        nonlocal edges, roots
        both = s.keep(edges.unionByName(more))
        s.drop(edges, roots, more)
        edges, roots = both, components(both, s)

    def place() -> DataFrame:
        """Members of buckets whose rows are not all linked, with their roots."""
        rows = s.keep(members.select("band", "id", "n").join(roots.toDF("id", "root"), "id", "left").withColumn("root", F.coalesce("root", "id")))
        hub = F.min(F.struct(F.xxhash64("id", F.lit(turn)).alias("h"), "id", "n", "root"))
        open_ = rows.groupBy("band").agg(F.min("root").alias("r1"), F.max("root").alias("r2"), hub.alias("hub")).where("r1 <> r2").select("band", "hub")
        out = s.keep(dealt(rows, open_, "band", hot, "id"))
        s.drop(rows)
        return out

    while True:
        rows = members if turn == 0 else placed.where("root <> hub.root")
        rows = rows.where((F.col("id") != F.col("hub.id")) & _near("n", "hub.n", percent))
        pairs = s.keep(rows.groupBy("id").agg(F.mode("hub.id", True).alias("a")).select("a", F.col("id").alias("b")))
        tried, new = pairs.count(), verify(pairs, full, percent, s)
        s.drop(pairs)
        found = new.count()
        if found:
            linked(new)
        turn += 1
        if placed is not None:
            s.drop(placed)
        placed = place()
        if found * 10 < max(tried, 1):
            break
    at = in_blocks(placed.select("band", "id", "root", F.lit(1).alias("w")), "band", "w", BLOCK_ROWS, s)
    tree = s.keep(forest(at.join(full.select("id", "n", "sig"), "id"), "band", percent, False))
    s.drop(placed)
    if not tree.isEmpty():
        near = components(tree, s)
        near = near.union(near.select(F.col("root").alias("node"), "root").distinct()).toDF("id", "near")
        rows = s.keep(near.join(roots.toDF("id", "root"), "id", "left").withColumn("root", F.coalesce("root", "id")).join(full.select("id", F.col("n").alias("w")), "id"))
        at = in_blocks(rows, "near", "w", BLOCK_ITEMS, s)
        new = s.keep(forest(at.join(full, "id"), "near", percent, True))
        s.drop(rows)
        if not new.isEmpty():
            linked(new)
    s.drop(tree)
    return roots, edges


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read(spark, sf_dir, "documents"), words=2, percent=80)


OP8_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), s AS (
  SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) = 1 THEN ws ELSE list_distinct(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1])) END AS sh FROM w
), e AS (SELECT doc_id, unnest(sh) AS x FROM s), p AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY 1, 2
), l AS (
  SELECT a, b FROM p JOIN s x ON x.doc_id = a JOIN s y ON y.doc_id = b WHERE 100 * c >= 80 * (len(x.sh) + len(y.sh) - c)
), r AS (SELECT doc_id AS a, doc_id AS b FROM s UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT s.doc_id, len(s.sh)::BIGINT AS n_shingles, min(r.b) AS component_id, s.doc_id = min(r.b) AS kept FROM s JOIN r ON r.a = s.doc_id GROUP BY s.doc_id, len(s.sh)
"""
