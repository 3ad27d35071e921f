"""Chat formatting of logged conversations with DataFrame functions only.

Logs often hold a conversation again and again as it grows. Every turn gets a rolling hash of all turns
up to it. A conversation whose last hash is another's hash at the same, inner turn is a prefix of it and
goes; of equal conversations the smallest id stays. Both are decided by joins on hashes: an anti-join with
the inner prefixes and a least id for each whole hash. What remains is rendered as one text with role
marks.

Defined cases: turns are ordered by number, equal numbers by role and text, and repeated rows count once; a
conversation is a prefix of another only if the turn numbers agree too; a null role or text counts as
empty, a null turn number as -1; rows without a conversation id are dropped; an empty table gives no rows;
other columns are not carried on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import cut, read

#: Turn numbers of a block of the rolling hash.
BLOCK = 64
OPEN, MIDDLE, CLOSE = "<|", "|>\n", "<|end|>\n"


def _turns(conversations: DataFrame, conv: str, turn: str, role: str, text: str) -> DataFrame:
    clean = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    return conversations.where(F.col(conv).isNotNull()).select(F.col(conv).alias("conv_id"), F.coalesce(F.col(turn), F.lit(-1)).cast("long").alias("turn"), clean(role).alias("role"), clean(text).alias("text"))


def prefixes(turns: DataFrame) -> DataFrame:
    """conv_id, turn, n and the 128-bit rolling hash (a, b) of all turns up to it; one row for each turn number.

    A turn's hashes hold its number, so their exclusive-or up to a turn is a hash of the sequence. It runs
    in two levels, over blocks of turn numbers and inside a block, so that one endless conversation isn't one window.
    """
    said = lambda seed: F.bit_xor(F.xxhash64(F.lit(seed), "turn", "role", "text"))
    rows = turns.distinct().groupBy("conv_id", "turn").agg(F.count("*").alias("n"), said(1).alias("a"), said(2).alias("b")).withColumn("block", F.floor(F.col("turn") / BLOCK))
    sums = rows.groupBy("conv_id", "block").agg(F.sum("n").alias("n0"), F.bit_xor("a").alias("a0"), F.bit_xor("b").alias("b0"))
    earlier = W.partitionBy("conv_id").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    none = F.lit(0).cast("long")
    before = sums.select("conv_id", "block", *(F.coalesce(f.over(earlier), none).alias(c) for f, c in ((F.sum("n0"), "n0"), (F.bit_xor("a0"), "a0"), (F.bit_xor("b0"), "b0"))))
    inside = W.partitionBy("conv_id", "block").orderBy("turn").rowsBetween(W.unboundedPreceding, 0)
    run = rows.select("conv_id", "block", "turn", F.sum("n").over(inside).alias("n"), F.bit_xor("a").over(inside).alias("a"), F.bit_xor("b").over(inside).alias("b"))
    return run.join(before, ["conv_id", "block"]).select("conv_id", "turn", (F.col("n") + F.col("n0")).alias("n"), F.col("a").bitwiseXOR(F.col("a0")).alias("a"), F.col("b").bitwiseXOR(F.col("b0")).alias("b"))


def maximal(turns: DataFrame) -> DataFrame:
    """conv_id and n_turns of the conversations that no other one continues or repeats under a smaller id."""
    known = cut(prefixes(turns))
    last = known.groupBy("conv_id").agg(F.max(F.struct("turn", "n", "a", "b")).alias("l")).select("conv_id", "l.*")
    ends = ["turn", "n", "a", "b"]
    least = last.groupBy(*ends).agg(F.min("conv_id").alias("conv_id"))
    inner = known.join(last.select("conv_id", F.col("turn").alias("end")), "conv_id").where("turn < end").select(*ends).distinct()
    return least.join(inner, ends, "left_anti").select("conv_id", F.col("n").alias("n_turns"))


def render(turns: DataFrame) -> DataFrame:
    """conv_id and the text of all turns in order with role marks."""
    one = turns.groupBy("conv_id").agg(F.sort_array(F.collect_set(F.struct("turn", "role", "text"))).alias("ts"))
    return one.select("conv_id", F.array_join(F.transform("ts", lambda t: F.concat(F.lit(OPEN), t["role"], F.lit(MIDDLE), t["text"], F.lit(CLOSE))), "").alias("rendered"))


def format_chats(conversations: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """One row for each maximal conversation: conv_id, n_turns, rendered."""
    turns = _turns(conversations, conv, turn, role, text)
    kept = cut(maximal(turns))
    return render(turns.join(kept.select("conv_id"), "conv_id", "left_semi")).join(kept, "conv_id").select("conv_id", "n_turns", "rendered")


def op3_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rendered text stands as its digest and length."""
    out = format_chats(read(spark, sf_dir, "conversations"))
    return out.select("conv_id", F.col("n_turns").cast("long").alias("n_turns"), F.length("rendered").cast("long").alias("n_chars"), F.sha2("rendered", 256).alias("rendered_sha256"))


OP3_SQL = r"""
WITH t AS (SELECT DISTINCT conv_id, coalesce(turn, -1) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL),
g AS (SELECT conv_id, turn, count(*) AS c, string_agg('<|' || role || '|>' || chr(10) || text || '<|end|>' || chr(10), '' ORDER BY role, text) AS s FROM t GROUP BY 1, 2),
r AS (SELECT conv_id, turn, sum(c) OVER w AS n, string_agg(s, '') OVER w AS s, string_agg(turn || ':' || s, '') OVER w AS k FROM g WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
e AS (SELECT conv_id, max(turn) AS turn, arg_max(n, turn) AS n, arg_max(s, turn) AS s, arg_max(k, turn) AS k FROM r GROUP BY conv_id)
SELECT min(e.conv_id) AS conv_id, e.n::BIGINT AS n_turns, length(e.s)::BIGINT AS n_chars, sha256(e.s) AS rendered_sha256
FROM e
WHERE NOT EXISTS (SELECT 1 FROM r JOIN e v ON v.conv_id = r.conv_id WHERE r.turn = e.turn AND r.k = e.k AND v.turn > e.turn)
GROUP BY e.n, e.s, e.k
"""
