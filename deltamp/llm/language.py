"""Language identification by a string kernel.

Two texts are as alike as the number of 1- to 3-grams that occur in both (presence, not counts),
divided by the root of the product of their own numbers. The regression is one-versus-rest kernel
ridge regression over a Nystroem map of landmark texts. A score is a product of three matrices, gram
presence x landmark presence x weights; the last two are multiplied once after the fit, so that a
batch of texts costs one sparse-by-dense product.

Grams are of code points in lower case, whatever the script; all that is no letter is one symbol, two
of which close a text. A gram has an exact 63-bit code: no alphabet is chosen and nothing is hashed.
Every language with a labelled row is learned; the rows of each, and so the model, are bounded.

Defined cases: a null text or one without a letter is ``und`` with score 0; with no training rows
every text is ``und``; repeated rows are scored alike; ties go to the smaller language name; other
columns are kept, but columns called like the results are replaced. A score only ranks the learned languages; the
cover, an optional result, tells whether a text is of the found language at all.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import textbuf
from .common import BROADCAST_BYTES, cut, free, read, remainder
from .grouped import caches, enter

_BITS = 21
#: Labelled rows learned from: at most so many of a language and of all (at least one of each language), and so many bytes
#: (the first row of a language counts whatever its size). Texts above ``LONG`` bytes are taken after all others.
PER_LANGUAGE, FIT_ROWS, FIT_BYTES, LONG = 600, 60_000, 32 << 20, 1 << 20
#: Landmarks at most, and distinct grams that they may have together (the first counts whatever its size).
LANDMARKS, LANDMARK_GRAMS = 256, 1 << 18
UNKNOWN = "und"


@dataclass(frozen=True)
class Model:
    languages: list[str]
    vocabulary: np.ndarray  # sorted codes of the grams of landmarks
    weights: np.ndarray  # (grams and one empty row, languages), or (.., landmarks) if there are more languages than these
    mix: np.ndarray | None  # (landmarks, languages), where it is not multiplied into the weights
    bias: np.ndarray
    known: list[np.ndarray]  # sorted 3-grams that the language's training texts hold often enough


@lru_cache(maxsize=1)
def _symbols() -> np.ndarray:
    """Symbol of each code point: 0 for no letter, else the letter in lower case."""
    table = np.zeros(0x110000, np.int64)
    for c in range(0x110000):
        if (ch := chr(c)).isalpha():
            table[c] = ord(low) if len(low := ch.lower()) == 1 else c
    return table


caches("language", _symbols.cache_clear)


def presence(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct 3-grams of each text (concatenated, sorted), the offset of each text, and whether it has a letter."""
    cps, at = textbuf.codepoints(raw, at)
    s = np.append(_symbols()[cps], np.zeros(2, np.int64))
    second, third = s[1:-1].copy(), s[2:].copy()
    last = at[1:][at[1:] > at[:-1]] - 1
    second[last] = third[last] = 0
    third[last[(last > 0)] - 1] = np.where(np.isin(last[last > 0] - 1, at[1:] - 1), third[last[last > 0] - 1], 0)
    codes = s[:-2] << 2 * _BITS | second << _BITS | third
    out, sizes, has = [], [], np.zeros(len(at) - 1, bool)
    for i in range(len(at) - 1):
        grams = np.sort(codes[at[i] : at[i + 1]])
        if len(grams):
            grams = grams[np.concatenate(([True], grams[1:] != grams[:-1]))]
            has[i] = grams[-1] >> 2 * _BITS > 0
        out.append(grams)
        sizes.append(len(grams))
    return np.concatenate(out) if out else np.empty(0, np.int64), np.concatenate(([0], np.cumsum(sizes, dtype=np.int64))), has


def blended(grams: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all 1-, 2- and 3-grams that are present (the shorter ones below zero), and the text of each."""
    row = np.repeat(np.arange(len(at) - 1), np.diff(at))
    parts, rows = [grams], [row]
    for n in (1, 2):
        short = grams >> n * _BITS
        first = np.ones(len(short), bool)
        first[1:] = (short[1:] != short[:-1]) | (row[1:] != row[:-1])
        parts.append(-1 - short[first] - (n - 1 << 2 * _BITS))
        rows.append(row[first])
    return np.concatenate(parts), np.concatenate(rows)


def _places(codes: np.ndarray, vocabulary: np.ndarray) -> np.ndarray:
    """Place of each code in the sorted vocabulary, its length for one that is not there."""
    if not len(vocabulary):
        return np.zeros(len(codes), np.int64)
    at = np.minimum(np.searchsorted(vocabulary, codes), len(vocabulary) - 1)
    return np.where(vocabulary[at] == codes, at, len(vocabulary))


def _sums(values: np.ndarray, places: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, values.shape[1]))
    for k in range(values.shape[1]):
        out[:, k] = np.bincount(rows, values[places, k], n)
    return out


def predict(column: pa.Array, model: Model) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Language, score and cover: the share of a text's distinct 3-grams with a letter that the language knows, whatever the other languages."""
    raw, at, _ = textbuf.utf8(column)
    names, scores, covers = [], [], []
    for i, j in textbuf.groups(at):
        if not model.languages:
            names += [UNKNOWN] * (j - i)
            scores.append(np.zeros(j - i))
            covers.append(np.zeros(j - i))
            continue
        grams, ends, has = presence(raw[at[i] : at[j]], at[i : j + 1] - at[i])
        codes, rows = blended(grams, ends)
        f = _sums(model.weights, _places(codes, model.vocabulary), rows, j - i) / np.sqrt(np.maximum(1, np.bincount(rows, minlength=j - i)))[:, None]
        f = (f if model.mix is None else f @ model.mix) + model.bias
        p = np.exp(4 * (f - f.max(1, keepdims=True)))
        best = f.argmax(1)
        names += [model.languages[b] if ok else UNKNOWN for b, ok in zip(best, has, strict=True)]
        scores.append(np.where(has, (p / p.sum(1, keepdims=True)).max(1), 0.0))
        row, lettered = np.repeat(np.arange(j - i), np.diff(ends)), grams > 0
        hit = np.zeros(j - i)
        for k in np.unique(best):
            mine = np.flatnonzero(lettered & (best[row] == k))
            hit += np.bincount(row[mine], _places(grams[mine], model.known[k]) < len(model.known[k]), j - i)
        covers.append(np.where(has, hit / np.maximum(1, np.bincount(row, lettered, j - i)), 0.0))
    return names, *(np.concatenate(x) if x else np.empty(0) for x in (scores, covers))


def _known(grams: list[np.ndarray]) -> np.ndarray:
    """A gram is known to a language if one of its texts in 200 has it."""
    found, n = np.unique(np.concatenate(grams), return_counts=True)
    return found[n >= len(grams) * 0.005]


def sample(docs: DataFrame, where, label: str, text: str, key: str) -> DataFrame:
    """(label, h, text) of the rows to learn from: of each language the distinct rows of the smallest hashes, within the bounds above.

    A first draw by hash, from an estimate of the distinct rows of each language, keeps what is shuffled small.
    """
    rows = docs.where(where & F.col(f"`{label}`").isNotNull() & F.col(f"`{text}`").isNotNull())
    rows = rows.select(F.col(f"`{label}`").alias("label"), F.col(f"`{text}`").alias("text"), F.xxhash64(F.col(f"`{key}`"), F.col(f"`{text}`")).alias("h"))
    counts = cut(rows.groupBy("label").agg(F.approx_count_distinct("h").alias("n")))
    many, size = counts.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("label") + 32), F.lit(0))).first()
    share, room = max(1, min(PER_LANGUAGE, FIT_ROWS // max(1, many))), FIT_BYTES // max(1, many)
    drawn = F.pmod(F.xxhash64("h"), F.lit(1 << 40)) / F.lit(float(1 << 40)) < F.lit(1.2 * share + 60) / F.greatest("n", F.lit(1))
    rows = rows.join(F.broadcast(counts) if size <= BROADCAST_BYTES else counts, "label").where(drawn)
    sizes = rows.groupBy("label", "h").agg(F.max(F.octet_length("text")).alias("size"))
    order = Window.partitionBy("label").orderBy(F.col("size") > LONG, "h")
    ranked = sizes.select("label", "h", F.row_number().over(order).alias("place"), F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("bytes"))
    picked = cut(ranked.where(F.col("place").between(1, share) & ((F.col("place") == 1) | (F.col("bytes") <= room))).select("label", "h"))
    few = picked.count() * 64 + size <= BROADCAST_BYTES
    return rows.join(F.broadcast(picked) if few else picked, ["label", "h"], "left_semi").groupBy("label", "h").agg(F.min("text").alias("text"))


def fit(docs: DataFrame, where, label: str = "lang", text: str = "text", key: str = "doc_id") -> Model:
    """Learns every language from a bounded number of the rows that ``where`` admits, see :func:`sample`."""

    def featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("language")
        for b in batches:
            raw, at, _ = textbuf.utf8(b.column("text"))
            for i, j in textbuf.groups(at):
                grams, ends, _ = presence(raw[at[i] : at[j]], at[i : j + 1] - at[i])
                yield pa.RecordBatch.from_arrays([b.column("label")[i:j], b.column("h")[i:j], pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(grams, pa.int64()))], ["label", "h", "grams"])

    data = sample(docs, where, label, text, key).mapInArrow(featurise, "label string, h long, grams array<long>").toArrow().sort_by([("label", "ascending"), ("h", "ascending")])
    if not data.num_rows:
        return Model([], np.empty(0, np.int64), np.zeros((1, 0), np.float32), None, np.zeros(0), [])
    return _solve(data.column("label").to_pylist(), [g.values.to_numpy() for g in data.column("grams")])


def _solve(labels: list[str], grams: list[np.ndarray], ridge: float = 1e-3) -> Model:
    languages, label = np.unique(np.array(labels, object), return_inverse=True)
    n, known = len(grams), [_known([grams[i] for i in np.flatnonzero(label == k)]) for k in range(len(languages))]
    chosen, vocabulary = [], np.empty(0, np.int64)
    for i in np.random.default_rng(7).permutation(n)[:LANDMARKS]:
        wider = np.union1d(vocabulary, blended(grams[i], np.array([0, len(grams[i])]))[0])
        if not chosen or len(wider) <= LANDMARK_GRAMS:
            chosen.append(i)
            vocabulary = wider
    codes = lambda i: blended(grams[i], np.array([0, len(grams[i])]))[0]
    marks = np.zeros((len(vocabulary) + 1, len(chosen)), np.float32)  # the last row: grams of no landmark
    for k, i in enumerate(chosen):
        marks[_places(codes(i), vocabulary), k] = 1
    size, cross = np.empty(n), np.empty((n, len(chosen)))
    for i in range(n):
        c = codes(i)
        size[i], cross[i] = np.sqrt(max(1, len(c))), marks[_places(c, vocabulary)].sum(0)
    cross /= size[:, None] * size[chosen]
    values, vectors = np.linalg.eigh(cross[chosen])
    keep = values > 1e-6
    root = vectors[:, keep] / np.sqrt(values[keep])
    phi = cross @ root
    y = np.where(label[:, None] == np.arange(len(languages)), 1.0, -1.0)
    mean, bias = phi.mean(0), y.mean(0)
    w = np.linalg.solve((phi - mean).T @ (phi - mean) + ridge * n * np.eye(phi.shape[1]), (phi - mean).T @ (y - bias))
    mix = (root @ w) / size[chosen][:, None]
    fold = len(languages) <= len(chosen)
    return Model(languages.tolist(), vocabulary, (marks @ mix).astype(np.float32) if fold else marks, None if fold else mix, bias - mean @ w, known)


def score(docs: DataFrame, model: Model, text: str = "text", label_out: str = "lang_pred", score_out: str = "score", cover_out: str | None = None) -> DataFrame:
    """``docs`` with the predicted language, its score and, if named, the cover; only the text goes to the Python workers."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("struct<a: string, b: double, c: double>")
    def predicted(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        enter("language")
        for part in parts:
            names, scores, covers = predict(part, shared.value)
            yield pa.StructArray.from_arrays([pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(covers, pa.float64())], ["a", "b", "c"])

    kept, p = [c for c in docs.columns if c not in (label_out, score_out, cover_out)], free(docs.columns, "_p")
    return docs.select(*(F.col(f"`{c}`") for c in kept), predicted(F.col(f"`{text}`")).alias(p)).select(*(F.col(f"`{c}`") for c in kept), F.col(f"{p}.a").alias(label_out), F.col(f"{p}.b").alias(score_out), *([F.col(f"{p}.c").alias(cover_out)] if cover_out else []))


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    held = remainder("doc_id", 4) == 2
    model = fit(docs, ~held)
    return score(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score")
