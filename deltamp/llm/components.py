"""Connected components of an edge table, distributed, by alternating contraction to stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, dealt, hot_keys


def components(edges: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """(node, root): each node of ``edges`` (a, b) but the smallest of its component, with that smallest one.

    Each round links every larger neighbour of a node to the node's least neighbour, then every smaller one
    likewise; it ends when only stars are left, after a number of rounds that is logarithmic in practice.
    The centre of a large star is a hot key of either join and is dealt over salts.
    """
    scratch = scratch or Scratch(edges.sparkSession, "components")
    e = scratch.keep(edges.where("a <> b").select(F.greatest("a", "b").alias("node"), F.least("a", "b").alias("root")).distinct())
    while not _stars(e):
        total = e.count()
        least = e.groupBy("node").agg(F.min("root").alias("m"))
        hot = hot_keys(e.groupBy("root").agg(F.count("*").alias("rows")), "root", total)
        # a root without a smaller neighbour stays what it is
        up = dealt(e, least.withColumnRenamed("node", "root"), "root", hot, "node", "left")
        large = scratch.keep(up.select("node", F.coalesce("m", "root").alias("root")).distinct())
        least = large.groupBy("node").agg(F.min("root").alias("m"))
        hot = hot_keys(large.groupBy("node").agg(F.count("*").alias("rows")), "node", total)
        small = dealt(large, least, "node", hot, "root").where("root <> m").select(F.col("root").alias("node"), F.col("m").alias("root"))
        new = scratch.keep(small.union(least.select("node", F.col("m").alias("root"))).distinct())
        scratch.drop(e, large)
        e = new
    return e


def _stars(e: DataFrame) -> bool:
    """Every node has one root, and no root is a node."""
    twice = e.groupBy("node").agg(F.count("*").alias("rows")).where("rows > 1").select("node")
    return twice.union(e.select(F.col("root").alias("node")).distinct().join(e.select("node").distinct(), "node", "left_semi")).isEmpty()
