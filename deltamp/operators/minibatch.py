"""Baselines that infer for groups of roots separately, so that shared neighbours are read again and again."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.functions.vectors import select_by_key
from deltamp.operators.dense import run_tail
from deltamp.operators.full import first_messages
from deltamp.operators.state import BROADCAST_BYTES, cut
from deltamp.plans.model import ModelSpec, Select, run_ops

#: Rows (batch, node) of the balls that are joined at a time.
WAVE_ROWS = 20_000_000
#: Numbers of gathered messages that are aggregated at a time.
PIECE = 1 << 22


def keyed_infer(roots: DataFrame, features: DataFrame, edges: DataFrame, model: ModelSpec) -> tuple[DataFrame, int]:
    """Outputs (batch_id, node_id, vec) of roots (batch_id, node_id), with every batch's in-ball apart; and all feature reads."""
    stages = model.stages()
    need = [cut(roots.select("batch_id", "node_id").distinct())]
    for stage in reversed(stages[1:]):
        sources = edges.join(need[0].withColumnRenamed("node_id", "dst"), "dst").select("batch_id", F.col("src").alias("node_id"))
        need.insert(0, cut((sources.unionByName(need[0]) if stage.self_term else sources).distinct()))
    # the first transform runs once for a node and batch, as each batch has its own copy
    first = first_messages(features, model)
    messages = cut(need[0].join(first, "node_id"))
    reads = messages.count()
    for s, stage in enumerate(stages[1:], 1):
        wanted = need[s]
        sent = edges.join(wanted.withColumnRenamed("node_id", "dst"), "dst").join(messages.withColumnRenamed("node_id", "src"), ["batch_id", "src"]).select("batch_id", "dst", "vec")
        agg = select_by_key(sent, ["batch_id", "dst"], stage.width, {"agg": (stage.marker.how, None)}).withColumnRenamed("dst", "node_id")
        rows = wanted.join(agg, ["batch_id", "node_id"], "left")
        if stage.self_term:
            rows = rows.join(messages.withColumnRenamed("vec", "own"), ["batch_id", "node_id"])
        # rows get one id through the dense part and back
        numbered = cut(rows.withColumn("_row", F.monotonically_increasing_id()))
        part = numbered.select(F.col("_row").alias("node_id"), "agg", *(["own"] if stage.self_term else []))
        messages = cut(run_tail(stage, part, model).withColumnRenamed("node_id", "_row").join(numbered.select("_row", "batch_id", "node_id"), "_row").select("batch_id", "node_id", "vec"))
    return messages, reads


def minibatch_infer(roots: DataFrame, features: DataFrame, edges: DataFrame, model: ModelSpec, batch_size: int = 16) -> tuple[DataFrame, int]:
    """Roots in batches of about ``batch_size`` (by hash, so that no global order is needed).

    The in-balls of all batches together grow with the square of the graph, so they are never written: a graph within
    the broadcast bound is placed once, and each task walks its batches' balls there. Others go through joins, some batches at a time.
    """
    n = max(1, -(-roots.count() // batch_size))
    keyed = roots.select(F.pmod(F.xxhash64("node_id"), F.lit(n)).cast("long").alias("batch_id"), "node_id")
    graph = loaded(roots, features, edges, model)
    return in_waves(keyed, n, features, edges, model) if graph is None else in_tasks(keyed, n, graph, model)


def in_waves(keyed: DataFrame, n: int, features: DataFrame, edges: DataFrame, model: ModelSpec) -> tuple[DataFrame, int]:
    """So many of the ``n`` batches at a time that their balls have ``WAVE_ROWS`` rows at most (one batch, if its ball alone may have more)."""
    step = max(1, WAVE_ROWS // max(1, features.count()))
    if step >= n:
        return keyed_infer(keyed, features, edges, model)
    keyed, parts = cut(keyed), []
    for lo in range(0, n, step):
        parts.append(keyed_infer(keyed.where((F.col("batch_id") >= lo) & (F.col("batch_id") < lo + step)), features, edges, model))
    return reduce(DataFrame.unionByName, [p for p, _ in parts]), sum(reads for _, reads in parts)


@dataclass
class Loaded:
    """A whole graph by position in ``ids``: features, and the sources of node v's in-edges at ``src[start[v]:start[v + 1]]``."""

    ids: np.ndarray
    vec: np.ndarray
    start: np.ndarray
    src: np.ndarray

    def sources(self, nodes: np.ndarray) -> np.ndarray:
        """Distinct in-neighbours."""
        hit, degree = np.zeros(len(self.ids), bool), self.start[nodes + 1] - self.start[nodes]
        for v in nodes[degree >= 256]:
            hit[self.src[self.start[v] : self.start[v + 1]]] = True
        for part, _, _ in self.pieces(nodes[(degree > 0) & (degree < 256)], 1 << 19):
            hit[part] = True
        return np.flatnonzero(hit)

    def pieces(self, nodes: np.ndarray, step: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Sources of the nodes' in-edges, ``step`` edges at a time, with the nodes' places and where each begins; each node has an in-edge."""
        first, ends = self.start[nodes], np.cumsum(self.start[nodes + 1] - self.start[nodes])
        total = int(ends[-1]) if len(nodes) else 0
        begins = np.concatenate([[0], ends[:-1]])
        for lo in range(0, total, step):
            hi = min(lo + step, total)
            at = np.arange(np.searchsorted(ends, lo, "right"), np.searchsorted(begins, hi, "left"))
            heads = np.maximum(begins[at], lo)
            where = np.repeat(first[at] - begins[at] + lo, np.minimum(ends[at], hi) - heads) + np.arange(hi - lo)
            yield self.src[where], at, heads - lo

    def aggregate(self, nodes: np.ndarray, messages: np.ndarray, how: str, fill: float) -> np.ndarray:
        """Element-wise best of the in-neighbours' messages, NaN above all numbers as in SQL; ``fill`` without an in-edge."""
        best, none = (np.fmin, np.nan) if how == "min" else (np.maximum, -np.inf)
        out = np.full((len(nodes), messages.shape[1]), fill)
        linked = np.flatnonzero(self.start[nodes + 1] > self.start[nodes])
        got = np.full((len(linked), messages.shape[1]), none)
        for part, at, heads in self.pieces(nodes[linked], max(1, PIECE // messages.shape[1])):
            got[at] = best(got[at], best.reduceat(messages[part], heads, axis=0))
        out[linked] = got
        return out


def loaded(roots: DataFrame, features: DataFrame, edges: DataFrame, model: ModelSpec) -> Loaded | None:
    """The graph, if it stays within the broadcast bound, a node has one row of features and all that are named have one."""
    stages = model.stages()
    if model.hooks.emit is not None or any(not isinstance(s.marker, Select) or s.marker.how not in ("min", "max") or s.joined for s in stages[1:]):
        return None
    n, m = features.count(), edges.count()
    if n * (16 + 8 * stages[0].width) + m * 4 > BROADCAST_BYTES:
        return None
    rows = features.select("node_id", "vec").toArrow()
    if not n or rows.column("node_id").null_count or rows.column("vec").null_count:
        return None
    ids, vec = rows.column("node_id").to_numpy(), rows.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False)
    if len(np.unique(ids)) < n or len(vec) != n * stages[0].width:
        return None
    order = np.argsort(ids)
    ids, vec = ids[order], vec.reshape(n, -1)[order]
    shared = edges.sparkSession.sparkContext.broadcast(ids)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            known, ends = shared.value, []
            for c in b.columns:
                x = c.to_numpy(zero_copy_only=False)
                p = np.minimum(np.searchsorted(known, x), len(known) - 1)
                ends.append(pa.array(np.where(known[p] == x, p, -1).astype(np.int32)))
            yield pa.RecordBatch.from_arrays(ends, ["src", "dst"])

    placed = edges.select("src", "dst").where("src IS NOT NULL AND dst IS NOT NULL").mapInArrow(place, "src int, dst int").toArrow()
    shared.destroy()
    src, dst = (placed.column(c).to_numpy() for c in ("src", "dst"))
    known = np.isin(roots.select("node_id").toArrow().column("node_id").to_numpy(), ids).all()
    if not known or (len(src) and min(src.min(), dst.min()) < 0):
        return None
    return Loaded(ids, vec, np.concatenate([[0], np.cumsum(np.bincount(dst, minlength=n))]), src[np.argsort(dst, kind="stable")])


def in_tasks(keyed: DataFrame, n: int, graph: Loaded, model: ModelSpec) -> tuple[DataFrame, int]:
    """Each batch on its own: its ball is walked back from the roots, then the stages run forward over the ball.

    A node's message of a stage is the same in every ball, as each holds all in-neighbours; a task keeps those that it
    has made, and later batches read them again. Reads count each batch's ball, repeats included.
    """
    sc = keyed.sparkSession.sparkContext
    shared = sc.broadcast((graph, model.stages(), model.empty_fill))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g, stages, fill = shared.value
        keys, nodes = [], []
        for b in batches:
            keys.append(b.column(0).to_numpy())
            nodes.append(b.column(1).to_numpy())
        if not keys:
            return
        keys, nodes = np.concatenate(keys), np.searchsorted(g.ids, np.concatenate(nodes))
        order = np.argsort(keys, kind="stable")
        numbers, begins = np.unique(keys[order], return_index=True)
        made: list = [None] * len(stages)
        has = [np.zeros(len(g.ids), bool) for _ in stages]

        def make(s: int, wanted: np.ndarray) -> None:
            new = wanted[~has[s][wanted]]
            if not len(new):
                return
            if s == 0:
                rows = run_ops(stages[0].tail, None, g.vec[new])
            else:
                agg = g.aggregate(new, made[s - 1], stages[s].marker.how, fill)
                rows = run_ops(stages[s].tail, agg, made[s - 1][new] if stages[s].self_term else agg)
            if made[s] is None:
                made[s] = np.empty((len(g.ids), rows.shape[1]))
            made[s][new], has[s][new] = rows, True

        for batch, roots in zip(numbers, np.split(nodes[order], begins[1:])):
            need = [np.unique(roots)]
            for stage in reversed(stages[1:]):
                found = g.sources(need[0])
                need.insert(0, np.union1d(found, need[0]) if stage.self_term else found)
            for s, wanted in enumerate(need):
                if made[s] is None and not len(wanted):  # a ball without an edge
                    made[s] = np.empty((len(g.ids), stages[s + 1].width))
                make(s, wanted)
            out, reads = made[-1][need[-1]], np.zeros(len(need[-1]), np.int64)
            reads[0] = len(need[0])
            ends = pa.array(np.arange(len(out) + 1) * out.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(out), batch)), pa.array(g.ids[need[-1]]), pa.ListArray.from_arrays(ends, pa.array(out.ravel())), pa.array(reads)], ["batch_id", "node_id", "vec", "reads"])

    dealt = keyed.repartition(min(n, 2 * sc.defaultParallelism), "batch_id")
    out = cut(dealt.mapInArrow(run, "batch_id long, node_id long, vec array<double>, reads long"))
    shared.destroy()
    return out.select("batch_id", "node_id", "vec"), out.agg(F.coalesce(F.sum("reads"), F.lit(0))).first()[0]


def ego_networks(roots: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """(root, node_id, hop): the directed in-ball of k hops of each root."""
    found = cut(roots.select(F.col("node_id").alias("root"), "node_id").withColumn("hop", F.lit(0)))
    front = found
    for hop in range(1, k + 1):
        step = edges.join(front.select("root", F.col("node_id").alias("dst")), "dst").select("root", F.col("src").alias("node_id")).distinct()
        front = cut(step.join(found, ["root", "node_id"], "left_anti").withColumn("hop", F.lit(hop)))
        found = cut(found.unionByName(front))
    return found


def ego_infer(roots: DataFrame, features: DataFrame, edges: DataFrame, model: ModelSpec) -> tuple[DataFrame, int]:
    """One ego network for each root, disjoint from all others."""
    return keyed_infer(roots.select(F.col("node_id").alias("batch_id"), "node_id"), features, edges, model)
