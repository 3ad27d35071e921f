"""Full inference, layer by layer over the whole graph."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.functions.vectors import select_by_key
from deltamp.operators.dense import run_tail
from deltamp.operators.state import State, cut
from deltamp.plans.model import Attention, ModelSpec, Stage, validate


def spread(edges: DataFrame, messages: DataFrame) -> DataFrame:
    """(dst, vec): each node's message along its out-edges."""
    return edges.join(messages.select(F.col("node_id").alias("src"), "vec"), "src").select("dst", "vec")


def aggregate(edges: DataFrame, messages: DataFrame, stage: Stage, keys: tuple[str, ...] = ()) -> DataFrame:
    """(node_id, agg) of every node with an in-edge."""
    if isinstance(stage.marker, Attention):
        return attention(edges, messages, stage.marker, stage.width)
    out = select_by_key(spread(edges, messages), ["dst"], stage.width, {"agg": (stage.marker.how, None)})
    return out.select(F.col("dst").alias("node_id"), "agg")


def attention(edges: DataFrame, messages: DataFrame, op: Attention, width: int) -> DataFrame:
    """Weights are a softmax, over the in-neighbours of a node, of a leaky linear score of both ends; then a weighted sum."""
    dot = lambda v, w: F.aggregate(F.zip_with(v, F.array(*(F.lit(float(x)) for x in np.ravel(w))), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    scored = messages.select("node_id", "vec", dot(F.col("vec"), op.left).alias("l"), dot(F.col("vec"), op.right).alias("r"))
    e = edges.join(scored.select(F.col("node_id").alias("src"), "vec", "l"), "src").join(scored.select(F.col("node_id").alias("dst"), "r"), "dst")
    e = e.withColumn("z", F.col("l") + F.col("r")).withColumn("z", F.when(F.col("z") < 0, F.col("z") * op.slope).otherwise(F.col("z")))
    top = e.groupBy("dst").agg(F.max("z").alias("top"))  # a shift that keeps exp in range
    e = e.join(top, "dst").withColumn("w", F.exp(F.col("z") - F.col("top")))
    weighted = select_by_key(e.selectExpr("dst", "transform(vec, x -> x * w) AS vec"), ["dst"], width, {"s": ("sum", None)})
    total = e.groupBy("dst").agg(F.sum("w").alias("t"))
    return weighted.join(total, "dst").select(F.col("dst").alias("node_id"), F.transform("s", lambda x: x / F.col("t")).alias("agg"))


def complete(nodes: DataFrame, aggregated: DataFrame) -> DataFrame:
    """Every node, a null aggregate where it has no in-edge."""
    return nodes.select("node_id").join(aggregated, "node_id", "left")


def first_messages(features: DataFrame, model: ModelSpec) -> DataFrame:
    return run_tail(model.stages()[0], features.select("node_id", F.col("vec").alias("own")), model)


def user_rows(model: ModelSpec, s: int, messages: DataFrame) -> DataFrame | None:
    """(node_id, vec) of the user's events when every message is new."""
    if model.hooks.emit is None:
        return None
    return model.hooks.merged(messages.select("node_id", F.lit(None).cast("array<double>").alias("old"), F.col("vec").alias("new")), s)


def next_messages(stage: Stage, aggregates: DataFrame, messages: DataFrame, model: ModelSpec, user: DataFrame | None = None) -> DataFrame:
    rows = aggregates.join(messages.select("node_id", F.col("vec").alias("own")), "node_id") if stage.self_term else aggregates
    if user is not None and model.hooks.apply is not None:
        rows = model.hooks.apply(rows, user)
    return run_tail(stage, rows, model)


def full_infer(features: DataFrame, edges: DataFrame, model: ModelSpec) -> DataFrame:
    """B1: (node_id, vec) on one snapshot, nothing kept. Attention, sums and means are allowed here."""
    nodes, messages = features.select("node_id"), first_messages(features, model)
    for s, stage in enumerate(model.stages()[1:], 1):
        messages = cut(messages)  # read twice: along the edges and as a self-term
        messages = next_messages(stage, complete(nodes, aggregate(edges, messages, stage)), messages, model, user_rows(model, s, messages))
    return messages


def bootstrap(features: DataFrame, edges: DataFrame, model: ModelSpec, state: State) -> None:
    """M1: one full pass whose messages and aggregates become version 0."""
    validate(model)
    nodes = features.select("node_id")
    state.edges.create(edges, 0)
    edges, n = state.edges.read(0), nodes.count()
    state.msg[1].create(first_messages(features, model), 0, n)
    for s, stage in enumerate(model.stages()[1:], 1):
        messages = state.msg[s].read(0)
        state.agg[s].create(complete(nodes, aggregate(edges, messages, stage)).withColumnRenamed("agg", "vec"), 0, n)
        user = user_rows(model, s, messages)
        if user is not None:
            state.user[s].create(user, 0, n)
            user = state.user[s].read(0)
        aggregates = state.agg[s].read(0).withColumnRenamed("vec", "agg")
        state.msg[s + 1].create(next_messages(stage, aggregates, messages, model, user), 0, n)
    state.start()
