"""The four cases of a target, decided position by position on reduced events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.functions.vectors import BLOCK, better, reset_mask

CASES = ("no_deletion", "deletion_no_effect", "covered_reset", "exposed_reset")


def classify(rows: DataFrame, how: str) -> DataFrame:
    """Adds ``condition`` to rows with ``old``, ``del_vec`` and ``add_vec``.

    A position is reset where the reduced cancel vector equals the old aggregate (the cancelled vectors were in it,
    so none is better). It is covered if the reduced add vector is at least as good there.
    """
    reset, good = "zip_with(old, del_vec, (o, d) -> o = d)", "<=" if how == "min" else ">="
    covered = f"forall(zip_with({reset}, zip_with(add_vec, old, (a, o) -> a {good} o), (r, c) -> NOT r OR c), x -> x)"
    none, harmless, filled, bare = CASES
    case = f"""CASE WHEN del_vec IS NULL OR old IS NULL THEN '{none}' WHEN NOT exists({reset}, r -> r) THEN '{harmless}'
      WHEN add_vec IS NOT NULL AND {covered} THEN '{filled}' ELSE '{bare}' END AS condition"""
    return rows.selectExpr("*", case)


def apply_incremental(rows: DataFrame, how: str) -> DataFrame:
    """Adds ``new``: the old aggregate selected with the adds; to be replaced where the reset is exposed."""
    best = "least" if how == "min" else "greatest"
    return rows.selectExpr("*", f"CASE WHEN old IS NULL THEN add_vec WHEN add_vec IS NULL THEN old ELSE zip_with(old, add_vec, (o, a) -> {best}(o, a)) END AS new")


def exposed_blocks(rows: DataFrame, how: str, width: int, block: int = BLOCK) -> DataFrame:
    """(dst, blk) of the exposed blocks of exposed targets: only these positions need their neighbours again."""
    open_ = F.zip_with(reset_mask(F.col("old"), F.col("del_vec")), F.coalesce(F.zip_with("add_vec", "old", lambda a, o: better(how, a, o)), F.array_repeat(F.lit(False), width)), lambda r, c: r & ~c)
    n = -(-width // block)
    return rows.select("dst", open_.alias("open")).withColumn("blk", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).where(F.exists(F.slice("open", F.col("blk") * block + 1, block), lambda x: x)).select("dst", "blk")
