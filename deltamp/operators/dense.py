"""The ops between two aggregations, on rows of vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.plans.model import ModelSpec, Stage, run_ops


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)


_placed: dict[tuple, tuple] = {}


def placed(spark: SparkSession, ops: tuple):
    """The ops' weights as a broadcast that all stages and batches of a session share; ``release`` ends it."""
    key = (spark.sparkContext.applicationId, *map(id, ops))
    if key not in _placed:
        _placed[key] = (spark.sparkContext.broadcast(ops), ops)  # the ops are held, so their identity stays theirs
    return _placed[key][0]


def release(model: ModelSpec) -> None:
    """Destroys the broadcasts of a model's ops."""
    mine = {id(op) for op in model.ops}
    for key in [k for k in _placed if mine & set(k[1:])]:
        _placed.pop(key)[0].destroy()


def run_tail(stage: Stage, rows: DataFrame, model: ModelSpec) -> DataFrame:
    """(node_id, vec): the stage's tail on ``rows`` (node_id, agg, own).

    Stage 0 reads ``own`` only. A null aggregate (no neighbour) is read as ``empty_fill``. ``own`` may be null
    where the tail has no self-term. Vectors cross to Python in Arrow batches, with the weights in a broadcast.
    """
    width = stage.width
    aggregated, ops, fill = stage.marker is not None, stage.tail, model.empty_fill
    shared = placed(rows.sparkSession, ops)
    filler = F.array_repeat(F.lit(fill), width)
    wide = stage.tail_width
    need_own = stage.self_term or not aggregated
    narrow = rows.select("node_id", F.coalesce("agg", filler).alias("x") if aggregated else F.col("own").alias("x"), *([F.col("own")] if need_own and aggregated else []))
    if not ops:
        return narrow.select("node_id", F.transform("x", lambda v: v + 0.0).alias("vec"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = _matrix(b.column(1), wide)
            own = _matrix(b.column(2), width) if b.num_columns > 2 else x
            y = run_ops(shared.value, x if aggregated else None, own)
            ends = pa.array(np.arange(len(y) + 1) * y.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(ends, pa.array(y.ravel()))], ["node_id", "vec"])

    return narrow.mapInArrow(run, "node_id long, vec array<double>")
