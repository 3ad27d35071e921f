"""Cost and accuracy measures."""

from __future__ import annotations

import inspect
import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.operators.extras import diff_count


def timed(action: Callable[[], object]) -> float:
    clock = time.perf_counter()
    action()
    return time.perf_counter() - clock


def to_noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def spread_of(seconds: list[float]) -> tuple[float, float]:
    """Median and 95th percentile of interval times."""
    ordered = sorted(seconds)
    return statistics.median(ordered), ordered[min(len(ordered) - 1, int(0.95 * len(ordered)))]


def area_ratio(area: DataFrame, nodes: DataFrame) -> DataFrame:
    """C4: nodes of the theoretical area over all nodes; one row."""
    a, n = area.agg(F.count("*").alias("n_area")), nodes.agg(F.count("*").alias("n_nodes"))
    return a.join(F.broadcast(n)).withColumn("ratio", F.col("n_area") / F.col("n_nodes"))


def condition_shares(stats: DataFrame) -> DataFrame:
    """Share of each case among the visited targets, over all stages and batches."""
    by = stats.groupBy("condition").agg(F.sum("n").alias("n"))
    total = by.agg(F.sum("n").alias("total"))
    return by.join(F.broadcast(total)).select("condition", "n", (F.col("n") / F.col("total")).alias("share"))


def condition_rollup(stats: DataFrame) -> DataFrame:
    return stats.rollup("stage", "condition").agg(F.sum("n").alias("n"))


def incremental_reads(reads: DataFrame) -> int:
    """Saved vectors that were read."""
    return reads.where("kind <> 'event'").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def storage_overhead(storage: DataFrame, feature_floats: int, n_edges: int) -> DataFrame:
    """Bytes of saved messages and aggregates over the bytes of features and edges."""
    data = feature_floats * 8 + n_edges * 16
    return storage.agg(F.sum("n_floats").alias("n_floats")).select("n_floats", F.lit(data).cast("long").alias("data_bytes"), (F.col("n_floats") * 8 / F.lit(data)).alias("overhead"))


def identical(a: DataFrame, b: DataFrame) -> bool:
    """C11: the same bits in every row."""
    return diff_count(a, b) == 0


def user_lines(maker: Callable) -> int:
    """Lines of a model's description."""
    return len([x for x in inspect.getsource(maker).splitlines()[1:] if x.strip() and not x.strip().startswith(('"""', "#"))])


def report(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)
