"""Affected-area inference: the theoretical k-hop area of changed edges, then ordinary inference for it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.operators.full import aggregate, complete, first_messages, next_messages
from deltamp.operators.state import Ids, cut, small
from deltamp.plans.model import ModelSpec


def at(edges, nodes: DataFrame, side: str) -> DataFrame:
    """The edges that have one of the distinct nodes at a side; ``edges`` is a frame or looked up by its nodes."""
    ids = Ids(nodes.select("node_id"), nodes.count())
    if isinstance(edges, DataFrame):
        return edges.join(small(ids.df.withColumnRenamed("node_id", side), ids.n), side, "left_semi")
    return edges.out_of(ids) if side == "src" else edges.into(ids)


def grow(seeds: DataFrame, edges, hops: int, side: tuple[str, str] = ("src", "dst")) -> DataFrame:
    """(node_id, hop): nodes within so many hops of the seeds along the edges, with the least hop."""
    here, there = side
    found = cut(seeds.select("node_id").distinct().withColumn("hop", F.lit(0)))
    front = found
    for hop in range(1, hops + 1):
        step = at(edges, front, here).select(F.col(there).alias("node_id")).distinct()
        front = cut(step.join(found, "node_id", "left_anti").withColumn("hop", F.lit(hop)))
        found = cut(found.unionByName(front))
    return found


def area(delta: DataFrame, before, after, k: int, mode: str = "source_ball") -> DataFrame:
    """(node_id, hop) of the theoretical area.

    ``source_ball``: k hops over old and new edges around the sources of changed edges. ``tight``: their targets and
    k - 1 hops on; each stage is seeded again, so the hops may use new edges alone, as a frame or looked up.
    """
    if mode == "source_ball":
        return grow(delta.select(F.col("src").alias("node_id")), before.unionByName(after).distinct(), k)
    return grow(delta.select(F.col("dst").alias("node_id")), after, k - 1)


def need_sets(targets: DataFrame, edges, model: ModelSpec) -> list[DataFrame]:
    """Nodes whose message of stage s (1 .. k + 1) is needed for the targets' outputs, walked backwards."""
    need = [cut(targets.select("node_id").distinct())]
    for stage in reversed(model.stages()[1:]):
        last = need[0]
        sources = at(edges, last, "dst").select(F.col("src").alias("node_id"))
        need.insert(0, cut((sources.unionByName(last) if stage.self_term else sources).distinct()))
    return need


def infer_for(targets: DataFrame, features: DataFrame, edges: DataFrame, model: ModelSpec) -> tuple[DataFrame, int]:
    """Outputs of the targets only, and the number of feature rows that were fetched."""
    need = need_sets(targets, edges, model)
    fetched = cut(features.join(small(need[0], need[0].count()), "node_id", "left_semi"))
    messages = first_messages(fetched, model)
    for s, stage in enumerate(model.stages()[1:], 1):
        wanted = need[s]
        mine = edges.join(small(wanted.select(F.col("node_id").alias("dst")), wanted.count()), "dst", "left_semi")
        messages = cut(messages)
        messages = cut(next_messages(stage, complete(wanted, aggregate(mine, messages, stage)), messages, model))
    return messages, fetched.count()


def affected_infer(features: DataFrame, before: DataFrame, after: DataFrame, delta: DataFrame, model: ModelSpec, mode: str = "tight") -> tuple[DataFrame, DataFrame, int]:
    """B2: (outputs of the area, the area, feature rows fetched). Rows outside keep what they had."""
    inside = area(delta, before, after, model.k, mode)
    out, fetched = infer_for(inside, features, after, model)
    return out, inside, fetched


def overlay(previous: DataFrame, fresh: DataFrame) -> DataFrame:
    return previous.join(fresh.select("node_id"), "node_id", "left_anti").unionByName(fresh)
