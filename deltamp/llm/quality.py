"""Quality classification by a generalised additive model with pairwise interactions.

Every text becomes a row of shape features (``FEATURES``). Each feature is cut into bins, and boosting
goes round the features in turn: each step fits one shallow tree on one feature's bins to the
gradient of the logistic loss and adds a small part of it to that feature's lookup table. The pairs
that explain most of what remains then get two-dimensional tables in the same way. A score is the
sum of one entry from each table, so a batch costs a few array lookups and additions.

Defined cases: a null text counts as empty; an empty text has all-zero features and gets the score of
its bins; without labelled rows (or with one class only) the score is the clipped share of label 1,
0.5 if there is none; several labels of one document count as their mean, rounded; other columns are
kept, those called like the results are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import textbuf
from .common import read, remainder
from .grouped import enter

#: Labelled rows at most that the fit uses, chosen by a hash of the id.
FIT_ROWS = 16_000
BINS, COARSE, PAIRS = 32, 8, 8
ROUNDS, PAIR_ROUNDS, RATE, LEAVES = 150, 60, 0.15, 4
THRESHOLD = 0.3

FEATURES = ("log_bytes", "upper", "digit", "bang", "bar", "symbol", "stop", "space", "wide", "word_bytes", "longest_word", "distinct_words", "repeated_next", "short_words", "line_words", "distinct_lines")

_UPPER, _LOWER, _DIGIT, _BANG, _BAR, _SYMBOL, _STOP, _SPACE, _LINE, _WIDE = range(10)


def _classes() -> np.ndarray:
    t = np.full(256, _SYMBOL, np.uint8)
    t[65:91], t[97:123], t[48:58], t[128:] = _UPPER, _LOWER, _DIGIT, _WIDE
    t[[ord(c) for c in ".,;:'\"-?"]] = _STOP
    t[ord("!")], t[ord("|")] = _BANG, _BAR
    t[[0x20, 9, 11, 12, 13]] = _SPACE
    t[10] = _LINE
    return t


_CLASS = _classes()


def features(column: pa.Array) -> np.ndarray:
    """One row of ``FEATURES`` for each text."""
    raw, at, _ = textbuf.utf8(column)
    parts = [_features(raw[at[i] : at[j]], at[i : j + 1] - at[i]) for i, j in textbuf.groups(at)]
    return np.concatenate(parts) if parts else np.empty((0, len(FEATURES)))


def _distinct(rows: np.ndarray, hashes: np.ndarray, n: int) -> np.ndarray:
    """Number of distinct hashes of each row."""
    keys = np.sort(rows.astype(np.uint64) << np.uint64(40) | hashes >> np.uint64(24))
    keys = keys[np.concatenate(([True], keys[1:] != keys[:-1]))] if len(keys) else keys
    return np.bincount((keys >> np.uint64(40)).astype(np.int64), minlength=n)


def _features(raw: np.ndarray, at: np.ndarray) -> np.ndarray:
    n, size = len(at) - 1, np.diff(at)
    kind = _CLASS[raw]
    row = np.repeat(np.arange(n), size)
    c = np.bincount(row * 10 + kind, minlength=n * 10).reshape(n, 10).astype(float)
    share = c / np.maximum(1, size)[:, None]
    symbols = textbuf.letters(256)[raw]
    starts, ends, first = textbuf.runs((kind != _SPACE) & (kind != _LINE), at)
    words, wrow, length = np.diff(first), row[starts], ends - starts
    h = textbuf.span_hashes(symbols, starts, ends)
    same = np.zeros(len(h), bool)
    same[1:] = (h[1:] == h[:-1]) & (wrow[1:] == wrow[:-1])
    most = np.maximum(1, words)
    longest = np.zeros(n)
    np.maximum.at(longest, wrow, length)
    ls, le, lfirst = textbuf.runs(kind != _LINE, at)
    lines = np.maximum(1, np.diff(lfirst))
    out = np.stack(
        [
            np.log1p(size), c[:, _UPPER] / np.maximum(1, c[:, _UPPER] + c[:, _LOWER] + c[:, _WIDE] / 2), share[:, _DIGIT], c[:, _BANG] / most, c[:, _BAR] / most, c[:, _SYMBOL] / most, c[:, _STOP] / most, share[:, _SPACE] + share[:, _LINE], share[:, _WIDE],
            np.bincount(wrow, length, n) / most, np.log1p(longest), _distinct(wrow, h, n) / np.sqrt(most) / 5, np.bincount(wrow, same, n) / most, np.bincount(wrow, length <= 3, n) / most, np.log1p(words / lines), _distinct(row[ls], textbuf.span_hashes(symbols, ls, le), n) / lines,
        ], 1,
    )
    out[size == 0] = 0
    return out


@dataclass
class Model:
    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)  # coarse bin of each bin
    pairs: list[tuple[int, int, np.ndarray]] = field(default_factory=list)

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, k], "right") for k, e in enumerate(self.edges)], 1)

    def scores(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.base)
        if self.edges and len(x):
            b = self.bins(x)
            for k, t in enumerate(self.tables):
                total += t[b[:, k]]
            for i, j, t in self.pairs:
                total += t[self.coarse[i][b[:, i]], self.coarse[j][b[:, j]]]
        return 1 / (1 + np.exp(-np.clip(total, -30, 30)))


def _tree(g: np.ndarray, h: np.ndarray, leaves: int) -> np.ndarray:
    """Step of each bin: the bins in order, cut greedily into at most so many leaves."""
    cg, ch = np.concatenate(([0], np.cumsum(g))), np.concatenate(([0], np.cumsum(h)))
    spans = [(0, len(g))]
    worth = lambda a, b: (cg[b] - cg[a]) ** 2 / (ch[b] - ch[a] + 1)
    while len(spans) < leaves:
        best = (1e-9, 0, 0)
        for k, (a, b) in enumerate(spans):
            if b - a > 1:
                cuts = np.arange(a + 1, b)
                gain = worth(a, cuts) + worth(cuts, b) - worth(a, b)
                m = int(gain.argmax())
                best = max(best, (float(gain[m]), k, int(cuts[m])))
        if not best[2]:
            break
        a, b = spans.pop(best[1])
        spans += [(a, best[2]), (best[2], b)]
    step = np.zeros(len(g))
    for a, b in spans:
        step[a:b] = (cg[b] - cg[a]) / (ch[b] - ch[a] + 1)
    return step


def _tree2(g: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, float]:
    """Step of each cell of a grid: one cut of the rows, then one cut of the columns on either side; its gain."""
    best, gain = np.zeros_like(g), -1.0
    for cut in range(1, g.shape[0]):
        step, total = np.zeros_like(g), 0.0
        for part in (slice(0, cut), slice(cut, None)):
            gs, hs = g[part].sum(0), h[part].sum(0)
            row = _tree(gs, hs, 2)
            step[part] = row
            total += float((row * gs).sum())
        if total > gain:
            best, gain = step, total
    return best, gain


def train(x: np.ndarray, y: np.ndarray) -> Model:
    if not len(y) or y.min() == y.max():
        share = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
        return Model(base=float(np.log(share / (1 - share))))
    m = Model(base=float(np.log(y.mean() / (1 - y.mean()))))
    for k in range(x.shape[1]):
        m.edges.append(np.unique(np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1])))
    sizes = [len(e) + 1 for e in m.edges]
    m.tables = [np.zeros(n) for n in sizes]
    m.coarse = [np.minimum(np.arange(n) * COARSE // max(n, 1), COARSE - 1) for n in sizes]
    b, total = m.bins(x), np.full(len(y), m.base)

    def slopes() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-total))
        return y - p, p * (1 - p)

    for _ in range(ROUNDS):
        for k, n in enumerate(sizes):
            g, h = slopes()
            step = RATE * _tree(np.bincount(b[:, k], g, n), np.bincount(b[:, k], h, n), LEAVES)
            m.tables[k] += step
            total += step[b[:, k]]
    cells = [m.coarse[k][b[:, k]] for k in range(len(sizes))]
    grid = lambda i, j, v: np.bincount(cells[i] * COARSE + cells[j], v, COARSE**2).reshape(COARSE, COARSE)
    g, h = slopes()
    ranked = sorted(combinations(range(len(sizes)), 2), key=lambda p: -_tree2(grid(*p, g), grid(*p, h))[1])[:PAIRS]
    tables = {p: np.zeros((COARSE, COARSE)) for p in ranked}
    for _ in range(PAIR_ROUNDS):
        for i, j in ranked:
            g, h = slopes()
            step = RATE * _tree2(grid(i, j, g), grid(i, j, h))[0]
            tables[i, j] += step
            total += step[cells[i], cells[j]]
    m.pairs = [(i, j, t) for (i, j), t in tables.items()]
    return m


def fit(docs: DataFrame, labels: DataFrame, where: Column, label: str = "quality", text: str = "text", key: str = "doc_id") -> Model:
    """Learns from at most ``FIT_ROWS`` labelled rows that ``where`` (over the key) admits."""
    known = labels.where(where & F.col(label).isNotNull()).groupBy(key).agg((F.avg(label) >= 0.5).cast("int").alias("_y"))
    n = known.count()
    if n:
        draw = F.pmod(F.xxhash64(F.col(key), F.lit(29)), F.lit(1 << 20))
        known = known.where(draw < int(min(1.0, FIT_ROWS / n) * (1 << 20)))
    rows = docs.select(key, F.col(text).alias("_t")).join(F.broadcast(known), key)  # the sample is bounded

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("quality")
        for b in batches:
            f = features(b.column(0))
            yield pa.RecordBatch.from_arrays([pa.FixedSizeListArray.from_arrays(pa.array(f.ravel()), len(FEATURES)).cast(pa.list_(pa.float64())), b.column(1), b.column(2)], ["f", "y", "k"])

    data = rows.select("_t", "_y", F.xxhash64(key).alias("k")).mapInArrow(measured, "f array<double>, y int, k long").toPandas().sort_values("k")
    return train(np.stack(data["f"].to_list()) if len(data) else np.empty((0, len(FEATURES))), data["y"].to_numpy(float))


def score(docs: DataFrame, model: Model, text: str = "text", score_out: str = "score", predicted_out: str = "predicted") -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def scored(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        enter("quality")
        for part in parts:
            yield pa.array(shared.value.scores(features(part)), pa.float64())

    kept = [F.col(f"`{c}`") for c in docs.columns if c not in (score_out, predicted_out)]
    return docs.select(*kept, scored(F.col(f"`{text}`")).alias(score_out)).withColumn(predicted_out, (F.col(score_out) >= THRESHOLD).cast("int"))


def op2_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    held = remainder("doc_id", 5) == 0
    model = fit(docs, read(spark, sf_dir, "labels"), ~held)
    return score(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "score", "predicted")
