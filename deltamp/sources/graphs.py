"""Streaming graphs on the given tables: each is a log of undirected changes and a node table.

A log row is (t, op, a, b) with a < b; ordered by (t, a, b) no two rows of a pair are equal. Node ids of
several kinds share one space: key * 4 + kind. Times of graphs without native deletions come from a hash of the pair.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F


_EPOCH = "1995-01-01"


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def pair_hash(a: Column, b: Column) -> Column:
    """Portable hash of a canonical pair; ids are reduced first, so that no product leaves 63 bits."""
    return (F.lit(1000003).cast("long") * (a % (1 << 20)) + F.lit(7919).cast("long") * (b % (1 << 20)) + 42) % F.lit(2147483647).cast("long")


def _canonical(pairs: DataFrame) -> DataFrame:
    return pairs.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), *[c for c in pairs.columns if c not in ("x", "y")])


def _simulated(pairs: DataFrame) -> DataFrame:
    """Log of pairs (x, y, t): an insert at t, and for one pair in five a delete 1 to 90 days later."""
    one = _canonical(pairs).groupBy("a", "b").agg(F.min("t").alias("t"))
    h = pair_hash(F.col("a"), F.col("b"))
    change = lambda t, op: F.struct(t.alias("t"), F.lit(op).alias("op"))
    add, gone = change(F.col("t"), "add"), change(F.col("t") + F.make_interval(days=(1 + h % 90).cast("int")), "del")
    return one.select(F.inline(F.when(h % 5 == 0, F.array(add, gone)).otherwise(F.array(add))), "a", "b")  # the pairs are made once


def _hashed_days(a: Column, b: Column) -> Column:
    return F.to_timestamp(F.lit(_EPOCH)) + F.make_interval(days=(pair_hash(F.least(a, b), F.greatest(a, b)) % 2000).cast("int"))


def user_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users and items of ``events``: an error event removes the link, any other sets it."""
    e = _read(spark, sf_dir, "events").select("ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k IS NOT NULL AND user_id IS NOT NULL")
    return _canonical(e.select(F.col("ts").alias("t"), F.when(F.col("event_type") == "error", "del").otherwise("add").alias("op"), (F.col("user_id") * 4).alias("x"), (F.col("k") * 4 + 1).alias("y"))).select("t", "op", "a", "b")


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and the parts that they ordered, from the first order date on."""
    o = _read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = _read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    return _simulated(o.join(li, o.o_orderkey == li.l_orderkey).select((F.col("o_custkey") * 4).alias("x"), (F.col("l_partkey") * 4 + 1).alias("y"), F.col("o_orderdate").alias("t")))


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts and suppliers of lineitem, from the first ship date on; few suppliers are hubs."""
    li = _read(spark, sf_dir, "lineitem")
    return _simulated(li.select((F.col("l_partkey") * 4 + 1).alias("x"), (F.col("l_suppkey") * 4 + 2).alias("y"), F.col("l_shipdate").alias("t")))


def vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three arithmetic links of each embedding."""
    e = _read(spark, sf_dir, "embeddings").select("vec_id")
    n = e.agg((F.max("vec_id") + 1).alias("n"))  # one row
    links = F.array(*(F.struct(F.lit(m).cast("long").alias("m"), F.lit(c).cast("long").alias("c")) for m, c in ((7, 3), (13, 5), (29, 11))))
    y = e.join(F.broadcast(n)).select("vec_id", "n", F.explode(links).alias("l")).select(F.col("vec_id").alias("x"), ((F.col("vec_id") * F.col("l.m") + F.col("l.c")) % F.col("n")).alias("y"))
    return _simulated(y.withColumn("t", _hashed_days(F.col("x"), F.col("y"))))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the distinct tokens that their links point to; a token's id is a portable hash of its bytes."""
    p = _read(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))).alias("tok")).distinct()
    return _simulated(p.select((F.col("page_id") * 4).alias("x"), (F.conv(F.substring(F.md5("tok"), 1, 10), 16, 10).cast("long") * 4 + 1).alias("y")).withColumn("t", _hashed_days(F.col("x"), F.col("y"))))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains: each turn of a conversation and the next."""
    c = _read(spark, sf_dir, "conversations").select("conv_id", "turn")
    nxt = c.withColumn("next", F.lead("turn").over(W.partitionBy("conv_id").orderBy("turn"))).where("next IS NOT NULL")
    ids = lambda t: F.col("conv_id") * 1000 + F.col(t)
    return _simulated(nxt.select(ids("turn").alias("x"), ids("next").alias("y")).withColumn("t", _hashed_days(F.col("x"), F.col("y"))))


GRAPHS = {"user_item": user_item, "cust_part": cust_part, "part_supp": part_supp, "vec": vec, "page_link": page_link, "turns": turns}


def nodes_of(log: DataFrame) -> DataFrame:
    """Every node that the log names: the vertex set is fixed over the stream."""
    return log.select(F.col("a").alias("node_id")).union(log.select("b")).distinct()


def hashed_features(nodes: DataFrame, width: int) -> DataFrame:
    """Wide, non-negative integer features by rule."""
    low = F.col("node_id") % 1048576
    feat = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: ((low * (2 * i + 3) + 7919 * i + 42) * F.lit(40503).cast("long") % 65521).cast("double"))
    return nodes.select("node_id", feat.alias("vec"))


def vector_features(spark: SparkSession, sf_dir: str, width: int = 64) -> DataFrame:
    """Embeddings quantised to integers that both engines hold exactly."""
    e = _read(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("node_id"), F.transform(F.slice("embedding", 1, width), lambda x: F.floor(x.cast("double") * 1024 + 0.5).cast("double") + 1024).alias("vec"))


def degree_index(edges: DataFrame, nodes: DataFrame, cap: int = 500) -> DataFrame:
    """Degree one-hot features as the index of the one, the last slot for all degrees from ``cap`` on."""
    degree = edges.groupBy(F.col("dst").alias("node_id")).agg(F.count("*").alias("n"))
    return nodes.join(degree, "node_id", "left").select("node_id", F.least(F.coalesce("n", F.lit(0)), F.lit(cap)).cast("int").alias("slot"))


def degree_onehot(edges: DataFrame, nodes: DataFrame, cap: int = 500) -> DataFrame:
    index = degree_index(edges, nodes, cap)
    return index.select("node_id", F.transform(F.sequence(F.lit(0), F.lit(cap)), lambda i: (i == F.col("slot")).cast("double")).alias("vec"))


def onehot_product(index: DataFrame, out: int, cap: int = 500) -> DataFrame:
    """A full weight matrix times a one-hot vector is a column of the matrix, given here by rule."""
    column = F.transform(F.sequence(F.lit(0), F.lit(out - 1)), lambda j: ((j * 7919 + F.col("slot") * 104729 + 42) % 4093).cast("double"))
    return index.select("node_id", column.alias("vec"))
