"""Snapshots, net changes and batches of a change log."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from deltamp.operators.state import BROADCAST_BYTES, Held, Ids, hold, ids_of, small


def pairs_after(log: DataFrame) -> DataFrame:
    """Pairs (a, b) whose last change is an insert. The last change is an algebraic aggregate, so hot pairs combine early."""
    return log.groupBy("a", "b").agg(F.max_by("op", "t").alias("op")).where("op = 'add'").select("a", "b")


def directed(pairs: DataFrame) -> DataFrame:
    """Both directions (src, dst) of undirected pairs."""
    keep = [c for c in pairs.columns if c not in ("a", "b")]
    return pairs.select(F.col("a").alias("src"), F.col("b").alias("dst"), *keep).unionByName(pairs.select(F.col("b").alias("src"), F.col("a").alias("dst"), *keep))


def snapshot(log: DataFrame) -> DataFrame:
    return directed(pairs_after(log))


class LogEdges:
    """The snapshot of a log, looked up by few nodes: their changes alone are grouped, and no snapshot is written.

    Pays off for a few lookups of nodes within the broadcast bound; more nodes are looked up in the whole snapshot.
    """

    def __init__(self, log: DataFrame) -> None:
        self.log = log

    def out_of(self, ids: Ids) -> DataFrame:
        if ids.n * 16 > BROADCAST_BYTES:
            return snapshot(self.log).join(ids.df.withColumnRenamed("node_id", "src"), "src", "left_semi")
        near = self.log
        for end in ("a", "b"):
            near = near.join(F.broadcast(ids.df.select(F.col("node_id").alias(end), F.lit(True).alias(f"{end}_in"))), end, "left")
        last = near.where("a_in OR b_in").groupBy("a", "b").agg(F.max_by("op", "t").alias("op"), F.max("a_in").alias("a_in"), F.max("b_in").alias("b_in")).where("op = 'add'")
        return last.where("a_in").select(F.col("a").alias("src"), F.col("b").alias("dst")).unionByName(last.where("b_in").select(F.col("b").alias("src"), F.col("a").alias("dst")))

    def into(self, ids: Ids) -> DataFrame:
        """Every edge has its opposite."""
        return self.out_of(ids).select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def intervals(log: DataFrame) -> DataFrame:
    """Directed temporal edges (src, dst, t_add, t_del), half open; a repeated insert opens nothing new."""
    w = W.partitionBy("a", "b").orderBy("t")
    flips = log.withColumn("before", F.lag("op").over(w)).where("NOT (op <=> before) AND NOT (before IS NULL AND op = 'del')")
    spans = flips.withColumn("t_del", F.lead("t").over(w)).where("op = 'add'").select("a", "b", F.col("t").alias("t_add"), "t_del")
    return directed(spans)


def snapshot_at(edges_t: DataFrame, t) -> DataFrame:
    return edges_t.where((F.col("t_add") <= t) & (F.col("t_del").isNull() | (F.lit(t) < F.col("t_del")))).select("src", "dst")


def latest_pairs(log: DataFrame, n: int = 500_000) -> DataFrame:
    """Newest ``n`` directed edges of the final snapshot: a bounded top-k, ties by the larger pair."""
    last = log.groupBy("a", "b").agg(F.max_by("op", "t").alias("op"), F.max("t").alias("t")).where("op = 'add'").select("a", "b", "t")
    return last.orderBy(F.desc("t"), F.desc("a"), F.desc("b")).limit(n // 2)


def newest(log: DataFrame, n: int) -> DataFrame:
    """The newest ``n`` changes of the log with their number from 0 on (a top-k, then a window over n rows)."""
    last = log.orderBy(F.desc("t"), F.desc("a"), F.desc("b")).limit(n)
    return last.withColumn("seq", F.row_number().over(W.orderBy("t", "a", "b")) - 1)


def without(log: DataFrame, changes: DataFrame) -> DataFrame:
    """The log before its newest changes."""
    edge = changes.agg(F.min(F.struct("t", "a", "b")).alias("e"))
    return log.join(F.broadcast(edge)).where(F.struct("t", "a", "b") < F.col("e")).drop("e")


def batches(changes: DataFrame, size: int) -> DataFrame:
    return changes.withColumn("batch", F.floor(F.col("seq") / size).cast("int"))


def net_delta(changes: DataFrame, edges) -> Held:
    """Net effect of one batch, (src, dst, op) in both directions: the last op of a pair, without inserts of present and deletes of absent edges."""
    last = changes.groupBy("a", "b").agg(F.max_by("op", F.struct("t", "seq")).alias("op"))
    delta = hold(directed(last))
    if isinstance(edges, DataFrame):
        near = edges.join(small(delta.df.select("src", "dst"), delta.n), ["src", "dst"], "left_semi")
    else:  # stored edges, or a log's: those of the sources alone
        near = edges.out_of(ids_of(delta, "src"))
    here = near.withColumn("here", F.lit(True))
    return hold(delta.df.join(here, ["src", "dst"], "left").where((F.col("op") == "add") == F.col("here").isNull()).select("src", "dst", "op"))
