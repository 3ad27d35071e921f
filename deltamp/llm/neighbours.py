"""Approximate nearest neighbours by an inverted multi-index.

The two halves of a vector are quantised separately, so two codebooks of K centroids make K * K cells; K grows with the
rows so that a cell has about ``CELL`` of them. A query takes the centroids of each half in order of distance and walks the
pairs by their summed squared distance with a heap, until the cells met hold a share of all rows. The share is
measured with the fit: on its sample, the least that finds ``RECALL`` of the true neighbours. The entries of the cells
met are reranked by the true distance. With ``share`` = 1 the search is exact.

Queries go to the cells that they aim at: entries and queries meet by (cell, part, block) of at most about ``PART`` entries
and ``BLOCK`` queries, so a cell with a third of all rows is many small groups, and rows of cells that no query
aims at are not read on. Each task gives at most k rows for a query, which a ranking merges. The codebooks are fitted on a
bounded sample of rows; every row is indexed.

Defined cases: vectors that are null, zero, of another length than most, or hold a null or non-finite
component take no part, neither as queries nor as candidates; rows without an id neither; ties go to the
smaller id, all of them are looked at; fewer candidates than k give fewer rows; an empty table gives none;
repeated rows of a candidate each count, repeated queries give one answer.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import cut, read
from .grouped import whole_groups

#: Rows that the fit uses at most, rows of a cell, centroids of a half at most, rounds of the fit.
FIT_ROWS, CELL, CENTROIDS, FIT_ROUNDS = 20_000, 64, 256, 12
#: Recall that the share of rows is chosen for, and queries of the sample that it is measured with.
RECALL, TRIALS = 0.97, 256
#: Entries and queries of a group, and results that a task holds before it merges them.
PART, BLOCK, HELD = 512, 1024, 500_000


@dataclass
class Index:
    entries: DataFrame  # id, cell, v (float64 bytes)
    codebooks: tuple[np.ndarray, np.ndarray]
    counts: np.ndarray  # rows of each cell
    share: float = 1.0  # of all rows that a search reads


def _vectors(column: pa.Array, dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a valid vector, and the vectors."""
    column = column.cast(pa.list_(pa.float64()))
    size = np.where(np.asarray(column.is_valid()), column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), 0)
    rows = np.flatnonzero(size == dim)
    flat = column.take(pa.array(rows)).flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
    ok = np.isfinite(flat).all(1) & (flat != 0).any(1)
    return rows[ok], flat[ok]


def _kmeans(x: np.ndarray, k: int) -> np.ndarray:
    x = x[np.lexsort(x.T[::-1])]
    c = np.unique(x[np.random.default_rng(3).permutation(len(x))[: 4 * k]], axis=0)
    c = c[np.random.default_rng(4).permutation(len(c))[:k]]
    for _ in range(FIT_ROUNDS):
        a = _nearest(x, c)
        n = np.bincount(a, minlength=len(c))
        sums = np.stack([np.bincount(a, x[:, d], len(c)) for d in range(x.shape[1])], 1)
        c = np.where(n[:, None] > 0, sums / np.maximum(1, n)[:, None], c)
    return c


def _nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return ((c**2).sum(1) - 2 * x @ c.T).argmin(1)


def build(vectors: DataFrame, key: str = "vec_id", column: str = "embedding") -> Index:
    spark = vectors.sparkSession
    rows = vectors.where(F.col(key).isNotNull() & F.col(column).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(column).alias("v"))
    sizes = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    dim, total = (sizes[0][0], sizes[0][1]) if sizes else (0, 0)
    draw = F.pmod(F.xxhash64("id", F.lit(5)), F.lit(1 << 20))
    sample = rows.where(draw < int(min(1.0, FIT_ROWS / max(1, total)) * (1 << 20)))

    def valid(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, x = _vectors(b.column(1), dim)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array([v.tobytes() for v in x], pa.binary())], ["id", "v"])

    if not dim:
        return Index(rows.select("id", F.lit(0).alias("cell"), F.lit(b"").alias("v")).limit(0), (np.zeros((1, 0)), np.zeros((1, 0))), np.zeros(1, np.int64))
    fit = sample.mapInArrow(valid, "id long, v binary").toPandas()
    x = np.frombuffer(b"".join(fit["v"]), float).reshape(-1, dim) if len(fit) else np.zeros((1, dim))
    half = dim // 2
    k = int(np.clip(round((total / CELL) ** 0.5), 2, CENTROIDS))
    codebooks = (_kmeans(x[:, :half], k), _kmeans(x[:, half:], k))
    width = len(codebooks[1])
    shared = spark.sparkContext.broadcast(codebooks)

    def assigned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at, x = _vectors(b.column(1), dim)
            cell = _nearest(x[:, :half], shared.value[0]) * width + _nearest(x[:, half:], shared.value[1])
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array(cell, pa.int32()), pa.array([v.tobytes() for v in x], pa.binary())], ["id", "cell", "v"])

    entries = cut(rows.mapInArrow(assigned, "id long, cell int, v binary"))
    counts = np.zeros(len(codebooks[0]) * width, np.int64)
    for r in entries.groupBy("cell").count().collect():  # at most CENTROIDS ** 2 rows
        counts[r[0]] = r[1]
    return Index(entries, codebooks, counts, _share(x, codebooks))


def _aims(x: np.ndarray, books: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Squared distances of the halves to their centroids."""
    half = books[0].shape[1]
    return tuple(np.maximum(0, (h**2).sum(1)[:, None] + (c**2).sum(1) - 2 * h @ c.T) for h, c in ((x[:, :half], books[0]), (x[:, half:], books[1])))


def _share(x: np.ndarray, books: tuple[np.ndarray, np.ndarray], k: int = 10) -> float:
    """Least share of the sample's rows in the cells met first that holds ``RECALL`` of its rows' true neighbours."""
    if len(x) < 4 * k:
        return 1.0
    tried = np.random.default_rng(8).permutation(len(x))[:TRIALS]
    left, right = _aims(x, books)
    width = right.shape[1]
    cell = left.argmin(1) * width + right.argmin(1)
    counts = np.bincount(cell, minlength=left.shape[1] * width)
    norm, needed = (x**2).sum(1), []
    for q in tried.tolist():
        d = norm - 2 * x @ x[q]
        d[q] = np.inf
        order = traverse(left[q], right[q], counts, len(x))
        met = np.zeros(len(counts))
        met[order] = np.cumsum(counts[order]) / len(x)
        needed.append(met[cell[np.argpartition(d, k)[:k]]])
    return float(np.quantile(np.concatenate(needed), RECALL, method="higher"))


def traverse(left: np.ndarray, right: np.ndarray, counts: np.ndarray, wanted: int) -> np.ndarray:
    """Cells by summed distance until ``wanted`` rows are met; ``left`` and ``right``: distance to each centroid."""
    a, b = np.argsort(left, kind="stable"), np.argsort(right, kind="stable")
    da, db, width = left[a].tolist(), right[b].tolist(), len(right)
    heap, met, seen = [(da[0] + db[0], 0, 0)], 0, []
    while heap and met < wanted:
        _, i, j = heapq.heappop(heap)
        cell = int(a[i]) * width + int(b[j])
        if counts[cell]:
            seen.append(cell)
            met += int(counts[cell])
        if j + 1 < width:
            heapq.heappush(heap, (da[i] + db[j + 1], i, j + 1))
        if j == 0 and i + 1 < len(da):
            heapq.heappush(heap, (da[i + 1] + db[0], i + 1, 0))
    return np.array(seen, np.int64)


def _exact(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Euclidean distances, the squares summed from the first component to the last."""
    return np.sqrt(np.add.accumulate((q - x) ** 2, axis=1)[:, -1])


def _best(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    return np.lexsort((ids, score))[:k]


def search(index: Index, where, k: int = 10, share: float | None = None) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest entries of each entry that ``where`` (over id) admits, itself left out."""
    spark, counts, books = index.entries.sparkSession, index.counts, index.codebooks
    wanted = max(k + 1, int(np.ceil((index.share if share is None else share) * counts.sum())))
    queries = index.entries.where(where).dropDuplicates(["id"])
    known = spark.sparkContext.broadcast((books, counts))

    def aimed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        books, counts = known.value
        for b in batches:
            x = np.frombuffer(b"".join(b.column(1).to_pylist()), float).reshape(b.num_rows, -1)
            left, right = _aims(x, books) if len(x) else (x, x)
            cells = [traverse(left[i], right[i], counts, wanted) for i in range(len(x))]
            ends = pa.array(np.concatenate(([0], np.cumsum([len(c) for c in cells]))), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.ListArray.from_arrays(ends, pa.array(np.concatenate([*cells, np.empty(0, np.int64)]), pa.int32()))], ["id", "v", "cells"])

    aimed_at = cut(queries.select("id", "v").mapInArrow(aimed, "id long, v binary, cells array<int>"))
    known.destroy()
    asked = aimed_at.select("id", "v", F.explode("cells").alias("cell"))
    met = asked.groupBy("cell").count().collect()  # at most CENTROIDS ** 2 rows
    if not met:
        return index.entries.select(F.col("id").alias("query_id"), F.lit(1).alias("rank"), F.col("id").alias("vec_id"), F.lit(0.0).alias("score")).limit(0)
    size = [(c, -(-int(counts[c]) // PART), -(-n // BLOCK)) for c, n in met]
    groups = F.broadcast(spark.createDataFrame(size, "cell int, parts long, blocks long"))
    dealt = lambda rows, one, n, each, m: rows.join(groups, "cell").withColumn(one, F.pmod(F.xxhash64("id"), F.col(n))).withColumn(each, F.explode(F.sequence(F.lit(0).cast("long"), F.col(m) - 1)))
    entries = dealt(index.entries, "part", "parts", "block", "blocks").withColumn("asks", F.lit(False))
    asking = dealt(asked, "block", "blocks", "part", "parts").withColumn("asks", F.lit(True))
    names = ["cell", "part", "block", "asks", "id", "v"]
    rows = entries.select(names).unionByName(asking.select(names)).repartition("cell", "part", "block").sortWithinPartitions("cell", "part", "block", "asks")

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        for t, starts in whole_groups(batches):
            asks, ids = t.column("asks").to_numpy(), t.column("id").to_numpy()
            x = np.frombuffer(b"".join(t.column("v").to_pylist()), float).reshape(len(ids), -1)
            for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(ids)], strict=True):
                m = a + int(np.searchsorted(asks[a:b], True))
                if a < m < b:
                    held.append(_ranked(ids[m:b], x[m:b], ids[a:m], x[a:m], k))
            if sum(map(len, held)) > HELD:
                held = [_top(np.concatenate(held), k)]
                if len(held[0]) > HELD:  # of too many queries to hold on
                    yield _batch(held.pop())
        if held:
            yield _batch(_top(np.concatenate(held), k))

    found = rows.mapInArrow(nearest, "query_id long, vec_id long, score double")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy("score", "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


_FOUND = np.dtype([("query_id", np.int64), ("vec_id", np.int64), ("score", np.float64)])


def _batch(found: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(found[c])) for c in _FOUND.names], list(_FOUND.names))


def _top(found: np.ndarray, k: int) -> np.ndarray:
    """The k best of each query."""
    found = found[np.lexsort((found["vec_id"], found["score"], found["query_id"]))]
    first = np.flatnonzero(np.concatenate(([True], found["query_id"][1:] != found["query_id"][:-1]))) if len(found) else np.empty(0, int)
    return found[np.arange(len(found)) - np.repeat(first, np.diff(np.append(first, len(found)))) < k]


def _ranked(qid: np.ndarray, q: np.ndarray, eid: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """The k entries nearest to each query, by the true distance."""
    norm = (q**2).sum(1)
    d = norm[:, None] + (x**2).sum(1) - 2 * q @ x.T
    d[qid[:, None] == eid] = np.inf
    bound = np.partition(d, min(k, d.shape[1]) - 1, axis=1)[:, min(k, d.shape[1]) - 1]
    out = []
    for i in range(len(qid)):
        near = np.flatnonzero((d[i] <= bound[i] + 1e-9 * (1 + norm[i])) & np.isfinite(d[i]))  # the slack covers the rounding of d
        score = _exact(q[i], x[near])
        keep = _best(score, eid[near], k)
        part = np.empty(len(keep), _FOUND)
        part["query_id"], part["vec_id"], part["score"] = qid[i], eid[near][keep], score[keep]
        out.append(part)
    return np.concatenate(out)


def op9_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(build(read(spark, sf_dir, "embeddings")), F.col("id") % 100 == 0)
