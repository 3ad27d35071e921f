"""Benchmark decontamination with DataFrame functions only.

A window is ``size`` consecutive words of a benchmark item (an item of fewer words is one window). Any
occurrence of a window of m words holds a whole block of b = (m + 1) // 2 words that starts at a multiple
of b, so a document gives one hash for every b words. The hashes of all b-grams of the windows are
the broadcast set (shuffled beyond its size bound). Documents with such a hash are read again; there all
windows of words are compared as text with the benchmark's windows, so a hash alone decides nothing.

Defined cases: words are runs of digits, a-z (A-Z in lower case) and non-ASCII characters; a null or wordless
text has 0 words and hits nothing; an empty benchmark hits nothing; null item texts and wordless items have no window;
repeated rows of documents give a row each; ``remove_*`` keep all columns of the documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, cut, free, read

SIZE = 10
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_WORD = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]*[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words(text: str) -> Column:
    return F.array_remove(F.split(F.translate(F.coalesce(F.col(text), F.lit("")), _UPPER, _LOWER), _BETWEEN), "")


def _grams(array: Column, size: int | Column, count: Column, step: int = 1) -> Column:
    """Slices of ``size`` words, one at every ``step``-th place, ``count`` of them."""
    return F.when(count > 0, F.transform(F.sequence(F.lit(0), (count - 1).cast("int")), lambda i: F.slice(array, i * step + 1, size))).otherwise(F.array().cast("array<array<string>>"))


def windows(benchmark: DataFrame, size: int = SIZE, item: str = "item_id", text: str = "text") -> DataFrame:
    """(m, words, items): distinct windows of m words with the sorted ids of the items that hold them."""
    b = benchmark.select(F.col(item).cast("string").alias("item"), words(text).alias("w")).withColumn("n", F.size("w")).where("n > 0 AND item IS NOT NULL")
    m = F.least(F.col("n"), F.lit(size))
    return b.select("item", m.alias("m"), F.explode(_grams(F.col("w"), m, F.col("n") - m + 1)).alias("words")).groupBy("m", "words").agg(F.sort_array(F.collect_set("item")).alias("items"))


def scan(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row for each document: key, h (hash of the text), n_words, hits (positions of hit words, from 0), items."""
    known = cut(windows(benchmark, size))
    lengths = [r[0] for r in known.select("m").distinct().collect()]  # at most ``size``
    half = (F.col("m") + 1) / 2
    blocks = known.select(F.explode(_grams(F.col("words"), F.floor(half).cast("int"), F.col("m") - F.floor(half) + 1)).alias("g")).select(F.xxhash64("g").alias("block")).distinct()
    blocks = cut(blocks.withColumn("hit", F.lit(1)))
    small = blocks.count() * 32 <= BROADCAST_BYTES
    base = docs.select(F.col(key).alias("doc_id"), F.xxhash64(text).alias("h"), words(text).alias("w")).withColumn("n_words", F.size("w").cast("long"))
    hashes = [F.transform(_grams(F.col("w"), b, F.floor(F.col("n_words") / b), b), lambda g: F.xxhash64(g)) for b in sorted({(m + 1) // 2 for m in lengths})]
    one = F.concat(*hashes) if hashes else F.array().cast("array<bigint>")
    rows = base.select("doc_id", "h", "n_words", F.posexplode_outer(one).alias("pos", "block"))
    seen = rows.join(F.broadcast(blocks) if small else blocks, "block", "left").groupBy("doc_id", "h").agg(F.max("n_words").alias("n_words"), F.max("hit").alias("hit"), F.sum(F.when(F.coalesce("pos", F.lit(0)) == 0, 1)).alias("rows"))
    seen = cut(seen)
    suspects = cut(seen.where("hit = 1").select("doc_id", "h"))
    few = suspects.count() * 24 <= BROADCAST_BYTES
    side = suspects.toDF("_k", "_h")
    again = base.join(F.broadcast(side) if few else side, (F.col("h") == F.col("_h")) & F.col("doc_id").eqNullSafe(F.col("_k")), "left_semi").dropDuplicates(["doc_id", "h"])
    told = lambda m: lambda x, i: F.struct(F.lit(m).alias("m"), i.alias("at"), F.concat_ws(" ", x).alias("t"))
    every = [F.transform(_grams(F.col("w"), m, F.col("n_words") - m + 1), told(m)) for m in sorted(lengths)]
    places = again.select("doc_id", "h", F.explode(F.concat(*every) if every else F.array().cast("array<struct<m:int,at:int,t:string>>")).alias("p")).select("doc_id", "h", "p.*")
    texts = known.select(F.concat_ws(" ", "words").alias("t"), "items")
    width = known.agg(F.sum(F.length(F.concat_ws(" ", "words")) * 2 + F.size("items") * 40)).first()[0] or 0
    found = places.join(F.broadcast(texts) if width <= BROADCAST_BYTES else texts, "t").groupBy("doc_id", "h").agg(F.collect_list(F.struct("at", "m")).alias("p"), F.collect_set("items").alias("i"))
    found = found.select(F.col("doc_id").alias("_k"), F.col("h").alias("_h"), F.array_distinct(F.flatten(F.transform("p", lambda x: F.sequence(x["at"], x["at"] + x["m"] - 1)))).alias("hits"), F.array_sort(F.array_distinct(F.flatten("i"))).alias("items"))
    out = seen.join(found, (F.col("h") == F.col("_h")) & F.col("doc_id").eqNullSafe(F.col("_k")), "left")
    empty = lambda c, kind: F.coalesce(F.col(c), F.array().cast(kind)).alias(c)
    out = out.select("doc_id", "h", "n_words", "rows", empty("hits", "array<int>"), empty("items", "array<string>"))
    return out.withColumn("_r", F.explode(F.array_repeat(F.lit(0), F.col("rows").cast("int")))).drop("_r", "rows")


def _matched(docs: DataFrame, benchmark: DataFrame, size: int, text: str, key: str) -> tuple[DataFrame, bool]:
    hit = cut(scan(docs, benchmark, size, text, key).where(F.size("hits") > 0).select(F.col("doc_id").alias("_k"), F.col("h").alias("_h"), F.col("hits").alias("_hits")).dropDuplicates(["_k", "_h"]))
    return hit, (hit.agg(F.sum(F.size("_hits") * 4 + 64)).first()[0] or 0) <= BROADCAST_BYTES


def remove_documents(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Documents that no window occurs in."""
    hit, few = _matched(docs, benchmark, size, text, key)
    k, h = (free(docs.columns, c) for c in ("_k", "_h"))
    side = hit.select(F.col("_k").alias(k), F.col("_h").alias(h))
    return docs.join(F.broadcast(side) if few else side, (F.xxhash64(docs[text]) == F.col(h)) & docs[key].eqNullSafe(F.col(k)), "left_anti")


def remove_spans(docs: DataFrame, benchmark: DataFrame, size: int = SIZE, text: str = "text", key: str = "doc_id") -> DataFrame:
    """All documents, the hit words (each with what separates it from the word before) taken out of the text."""
    hit, few = _matched(docs, benchmark, size, text, key)
    k, h, hits = (free(docs.columns, c) for c in ("_k", "_h", "_hits"))
    side = hit.toDF(k, h, hits)
    both = docs.join(F.broadcast(side) if few else side, (F.xxhash64(docs[text]) == F.col(h)) & docs[key].eqNullSafe(F.col(k)), "left")
    parts = F.regexp_extract_all(F.col(text), F.lit(_WORD), F.lit(0))
    tail = F.regexp_extract(F.col(text), r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]*$", 0)
    marked = F.map_from_entries(F.transform(hits, lambda i: F.struct(i, F.lit(True))))
    left = F.concat(F.array_join(F.filter(parts, lambda x, i: ~F.map_contains_key(marked, i)), ""), tail)
    return both.withColumn(text, F.when(F.col(hits).isNull(), F.col(text)).otherwise(left)).select(*docs.columns)


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", F.size("hits").cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"))


OP10_SQL = r"""
WITH d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents
), b AS (
  SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark
), m AS (
  SELECT DISTINCT item_id::VARCHAR AS item, least(len(w), 10) AS m, array_to_string(w[i:i + least(len(w), 10) - 1], ' ') AS t
  FROM (SELECT item_id, w, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM b WHERE len(w) > 0)
), p AS (
  SELECT doc_id, i, n.m, array_to_string(w[i:i + n.m - 1], ' ') AS t
  FROM (SELECT DISTINCT m FROM m) n, LATERAL (SELECT doc_id, w, unnest(range(1, len(w) - n.m + 2)) AS i FROM d)
), h AS (SELECT p.doc_id, p.i, p.m, m.item FROM p JOIN m ON p.m = m.m AND p.t = m.t), c AS (
  SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + m)) AS q FROM h) GROUP BY 1
), g AS (
  SELECT doc_id, count(*) AS n_items, sha256(string_agg(item, ',' ORDER BY item)) AS s FROM (SELECT DISTINCT doc_id, item FROM h) GROUP BY 1
)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, coalesce(s, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN g USING (doc_id)
"""
