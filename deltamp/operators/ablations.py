"""What grouping is for: events applied one by one, without it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fold_events(attached: DataFrame, old: DataFrame, how: str) -> DataFrame:
    """(dst, old, new) with each event applied on its own: a cancel resets equal positions, an add selects. Wrong on purpose.

    Cancels come first. A reset position is null until an add fills it, and a value that another neighbour held is lost.
    """
    f = F.least if how == "min" else F.greatest  # both skip nulls
    events = attached.groupBy("dst").agg(F.sort_array(F.collect_list(F.struct((F.col("op") == "add").alias("add"), "vec"))).alias("es"))
    rows = events.join(old, "dst", "left")
    apply = lambda acc, e: F.when(e["add"], F.zip_with(acc, e["vec"], lambda x, y: f(x, y))).otherwise(F.zip_with(acc, e["vec"], lambda x, y: F.when(x == y, F.lit(None).cast("double")).otherwise(x)))
    start = F.coalesce("old", F.transform(F.col("es")[0]["vec"], lambda x: F.lit(None).cast("double")))
    return rows.withColumn("new", F.aggregate("es", start, apply)).drop("es")
