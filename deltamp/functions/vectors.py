"""Element-wise functions over ``array<double>`` columns, all native expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Positions of one aggregation block: few enough columns for generated code, few enough rows for wide vectors.
BLOCK = 32


def better(how: str, x: Column, y: Column) -> Column:
    """x is at least as good as y."""
    return x <= y if how == "min" else x >= y


def pick(how: str, a: Column, b: Column) -> Column:
    """Element-wise best of two vectors; a null vector is the identity."""
    f = F.least if how == "min" else F.greatest
    return F.when(a.isNull(), b).when(b.isNull(), a).otherwise(F.zip_with(a, b, lambda x, y: f(x, y)))


def reset_mask(old: Column, cancelled: Column) -> Column:
    """Positions at which the old aggregate equals the reduced cancel vector."""
    return F.zip_with(old, cancelled, lambda x, y: x == y)


def unnest(df: DataFrame, vec: str = "vec", key: str = "node_id") -> DataFrame:
    """Long rows (key, dim, val)."""
    return df.select(key, F.posexplode(vec).alias("dim", "val"))


_SQL = {"min": "min", "max": "max", "sum": "sum", "mean": "avg"}


def select_by_key(df: DataFrame, key: list[str], width: int, aggregates: dict[str, tuple[str, str | None]], vec: str = "vec", block: int = BLOCK) -> DataFrame:
    """Element-wise aggregates of vectors by key, each under its name as (how, SQL condition).

    The vectors are cut into blocks of positions, and a block's positions are plain aggregate columns, so map-side
    partial aggregation holds ``block`` numbers for a key and never a neighbourhood. A group without a row that
    meets the condition has a null vector. The plan is one SQL statement, as it has a column for each position.
    """
    keys = ", ".join(key)

    def columns(n: int, at: str) -> str:
        cell = lambda how, cond, i: f"{_SQL[how]}({at.format(i) if cond is None else f'CASE WHEN {cond} THEN {at.format(i)} END'})"
        return ", ".join(f"{cell(how, cond, i)} AS {name}_{i}" for name, (how, cond) in aggregates.items() for i in range(n))

    def gathered(n: int) -> str:
        return ", ".join(f"CASE WHEN {name}_0 IS NOT NULL THEN array({', '.join(f'{name}_{i}' for i in range(n))}) END AS {name}" for name in aggregates)

    run = df.sparkSession.sql
    if width <= block:
        return run(f"SELECT {keys}, {gathered(width)} FROM (SELECT {keys}, {columns(width, vec + '[{}]')} FROM {{df}} GROUP BY {keys})", df=df)
    n = -(-width // block)
    inner = f"SELECT *, slice({vec}, _b * {block} + 1, {block}) AS _v FROM {{df}} LATERAL VIEW explode(sequence(0, {n - 1})) AS _b"
    parts = f"SELECT {keys}, _b, {gathered(block)} FROM (SELECT {keys}, _b, {columns(block, 'get(_v, {})')} FROM ({inner}) GROUP BY {keys}, _b)"
    listed = ", ".join(f"sort_array(collect_list(CASE WHEN {name} IS NOT NULL THEN struct(_b, {name}) END)) AS {name}" for name in aggregates)
    joined = ", ".join(f"CASE WHEN size({name}) > 0 THEN slice(flatten(transform({name}, s -> s.{name})), 1, {width}) END AS {name}" for name in aggregates)
    return run(f"SELECT {keys}, {joined} FROM (SELECT {keys}, {listed} FROM ({parts}) GROUP BY {keys})", df=df)


#: SQL functions by name: arguments, type and expression.
SQL_FUNCTIONS = {
    "vec_min": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> least(x, y))"),
    "vec_max": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> greatest(x, y))"),
    "vec_dot": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    "vec_relu": ("a ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "transform(a, x -> greatest(x, 0D))"),
    "vec_argdiff": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<INT>", "filter(transform(a, (x, i) -> if(x <=> b[i], null, i)), i -> i IS NOT NULL)"),
}


def register(spark: SparkSession) -> None:
    """Makes ``vec_*`` callable from SQL, and ``vec_unnest(vec)`` as a table function."""
    for name, (arguments, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_unnest(v ARRAY<DOUBLE>) RETURNS TABLE(dim INT, val DOUBLE) RETURN SELECT pos, col FROM (SELECT posexplode(v))")
