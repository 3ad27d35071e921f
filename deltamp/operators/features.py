"""Changes of the node table: new features, new nodes, removed nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.operators.full import first_messages, next_messages, user_rows
from deltamp.operators.state import hold, ids_of


def apply_features(session, features: DataFrame) -> DataFrame:
    """New features (node_id, vec) of known nodes; returns the changed outputs (node_id, version, vec)."""
    from deltamp.operators.incremental import advance

    fresh = hold(first_messages(features, session.model).withColumnRenamed("vec", "new"))
    old = session.state.msg[1].lookup(ids_of(fresh)).withColumnRenamed("vec", "old")
    changed = hold(fresh.df.join(old, "node_id").where(~F.col("new").eqNullSafe(F.col("old"))).select("node_id", "old", "new"))
    none = hold(session.spark.createDataFrame([], "src long, dst long, op string"))
    return session.take(advance(session.state, none, session.model, session.options, changed))[0]


def insert_nodes(session, features: DataFrame) -> None:
    """Nodes without edges yet: their aggregates are null at every stage; their edges come as changes after that."""
    state, model, writes = session.state, session.model, []
    vec = hold(first_messages(features, model))
    for s, stage in enumerate(model.stages()[1:], 1):
        writes.append((f"msg_{s}", vec.df))
        empty = vec.df.select("node_id", F.lit(None).cast("array<double>").alias("vec"))
        writes.append((f"agg_{s}", empty))
        user = user_rows(model, s, vec.df)
        if user is not None:
            writes.append((f"user_{s}", user))
        vec = hold(next_messages(stage, empty.withColumnRenamed("vec", "agg"), vec.df, model, user))
    state.commit([*writes, (f"msg_{model.k + 1}", vec.df)])


def delete_nodes(session, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Removes all edges of the nodes (node_id); the nodes stay, without neighbours."""
    found = ids_of(hold(ids.select("node_id").distinct()))
    gone = session.edges.out_of(found).unionByName(session.edges.into(found)).distinct()
    return session.apply_delta(gone.withColumn("op", F.lit("del")))
