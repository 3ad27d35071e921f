"""Events: which targets must look at which vectors again.

An event is (dst, op, src, side): op 'del' cancels and 'add' offers the vector of ``src``, as it was before the
batch or is after it. Events are narrow; the vectors are joined late, once for each (src, side).
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from deltamp.functions.vectors import select_by_key

SIDES = {"del": "before", "add": "after"}


def seed_events(delta: DataFrame) -> DataFrame:
    """Changed edges: a removed one cancels what its source sent before, a new one offers what its source sends now."""
    return delta.selectExpr("dst", "op", "src", f"if(op = 'del', '{SIDES['del']}', '{SIDES['add']}') AS side")


def frontier_events(before: DataFrame, after: DataFrame) -> DataFrame:
    """Nodes whose message changed cancel the old one along their old edges and offer the new one along their new edges (src, dst)."""
    part = lambda edges, op: edges.selectExpr("dst", f"'{op}' AS op", "src", f"'{SIDES[op]}' AS side")
    return part(before, "del").unionByName(part(after, "add"))


def attach(events: DataFrame, messages: DataFrame, share: bool = True) -> DataFrame:
    """(dst, op, vec). ``messages``: (src, side, vec), one row for each vector that an event names.

    With ``share`` off each event carries its vector from the start, which moves a vector once for each event.
    """
    if share:
        return events.join(messages, ["src", "side"]).select("dst", "op", "vec")
    return events.join(messages, ["src", "side"]).repartition("dst").select("dst", "op", "vec")


def reduce_events(attached: DataFrame, how: str, width: int) -> DataFrame:
    """(dst, del_vec, add_vec): both ops of a target reduced in one shuffle; null where a target has no event of the op."""
    return select_by_key(attached, ["dst"], width, {"del_vec": (how, "op = 'del'"), "add_vec": (how, "op = 'add'")})
