"""Sampling, pooling, the choice of a method, scores of links, differences of results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from deltamp.functions.vectors import select_by_key
from deltamp.sources.graphs import pair_hash


def cached_sample(edges: DataFrame, fanout: int, seed: int = 0, salts: int = 1) -> DataFrame:
    """(src, dst, kept): at most ``fanout`` in-edges of a node by a seeded hash, as a flag that stays with the edge.

    With ``salts`` > 1 a hub's edges are ranked in parts first, and only the parts' winners meet.
    """
    h = (pair_hash(F.col("src"), F.col("dst")) + F.lit(seed * 104729)) % F.lit(2147483647).cast("long")
    rows = edges.select("src", "dst", h.alias("h"))
    if salts > 1:
        part = W.partitionBy("dst", F.pmod("h", F.lit(salts))).orderBy("h", "src")
        rows = rows.withColumn("first", F.row_number().over(part)).withColumn("in", F.col("first") <= fanout)
        ranked = rows.where("in").withColumn("r", F.row_number().over(W.partitionBy("dst").orderBy("h", "src"))).select("src", "dst", (F.col("r") <= fanout).alias("kept"))
        return ranked.unionByName(rows.where("NOT in").select("src", "dst", F.lit(False).alias("kept")))
    return rows.withColumn("r", F.row_number().over(W.partitionBy("dst").orderBy("h", "src"))).select("src", "dst", (F.col("r") <= fanout).alias("kept"))


def extend_sample(sample: DataFrame, delta: DataFrame) -> DataFrame:
    """The sample after a batch: earlier flags stand, inserted edges are always kept."""
    left = sample.join(delta.select("src", "dst"), ["src", "dst"], "left_anti")
    return left.unionByName(delta.where("op = 'add'").select("src", "dst", F.lit(True).alias("kept")))


def sampled_delta(sample: DataFrame, delta: DataFrame) -> DataFrame:
    """The net changes that a sample sees: deletes of edges that it keeps, and all inserts."""
    gone = delta.where("op = 'del'").join(sample.where("kept").select("src", "dst"), ["src", "dst"], "left_semi")
    return gone.select("src", "dst", "op").unionByName(delta.where("op = 'add'").select("src", "dst", "op"))


def pool(outputs: DataFrame, groups: DataFrame, width: int, how: str = "sum") -> DataFrame:
    """(group_id, vec): pooled outputs of the members (node_id, group_id)."""
    return select_by_key(outputs.join(groups, "node_id"), ["group_id"], width, {"pooled": (how, None)}).select("group_id", F.col("pooled").alias("vec"))


def choose(n_touched: int, n_nodes: int, exposed_share: float, limit: float = 0.5) -> str:
    """'full' where watching costs more than it saves: the area is most of the graph, or most targets must be recomputed."""
    share = n_touched / max(1, n_nodes)
    return "full" if share > limit or share * (1 + 4 * exposed_share) > limit else "incremental"


def link_scores(outputs: DataFrame, links: DataFrame) -> DataFrame:
    """(a, b, score): the product of both ends' outputs."""
    x, y = outputs.select(F.col("node_id").alias("a"), F.col("vec").alias("va")), outputs.select(F.col("node_id").alias("b"), F.col("vec").alias("vb"))
    dot = F.aggregate(F.zip_with("va", "vb", lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return links.join(x, "a").join(y, "b").select("a", "b", dot.alias("score"))


def diff_count(a: DataFrame, b: DataFrame) -> int:
    """Rows by which two results differ, both ways; 0 means identical bits."""
    return a.exceptAll(b).unionAll(b.exceptAll(a)).count()
