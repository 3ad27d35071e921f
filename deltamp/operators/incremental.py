"""Incremental inference: brings every message and aggregate to the next version, touching what changed."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.functions.vectors import BLOCK, pick, select_by_key
from deltamp.operators.ablations import fold_events
from deltamp.operators.classify import apply_incremental, classify, exposed_blocks
from deltamp.operators.dense import release, run_tail
from deltamp.operators.events import attach, frontier_events, reduce_events, seed_events
from deltamp.operators.full import bootstrap
from deltamp.operators.state import Held, State, cut, hold, hold_equal, ids_of, small
from deltamp.plans.model import ModelSpec, Stage, validate
from deltamp.sources.temporal import net_delta

STATS = "batch int, stage int, condition string, evolved boolean, n long"
READS = "batch int, stage int, kind string, n long"


@dataclass
class Options:
    propagate: str = "on_change"  # or "eager": covered and recomputed targets always go on
    compare: str = "aggregate"  # or "message": a touched node goes on only if its message differs
    recompute_scope: str = "node"  # or "block": only exposed blocks are gathered again
    dedupe: bool = False
    share: bool = True
    early_stop: bool = True
    mode: str = "grouped"  # or "recompute_all", "ungrouped" (wrong on purpose)


@dataclass
class Step:
    changed: DataFrame  # node_id, old, new messages of the last stage
    stats: list[tuple] = field(default_factory=list)
    reads: list[tuple] = field(default_factory=list)
    phases: dict[str, float] = field(default_factory=dict)


def recompute(exposed: Held, delta: Held, state: State, s: int, changed: Held, stage: Stage, open_blocks: Held | None = None) -> tuple[DataFrame, int, DataFrame]:
    """(dst, again): the select over all current in-neighbours of the exposed targets, the number of messages read, and the pulled edges."""
    targets = ids_of(exposed, "dst")
    pulls = hold(state.edges.after(state.edges.into(targets), delta.df, targets, "dst"))
    sources = ids_of(pulls, "src")
    stored = state.msg[s].lookup(sources)
    held = stored.join(small(changed.df.select("node_id", "new"), changed.n, 16 + 8 * stage.width), "node_id", "left").select(F.col("node_id").alias("src"), F.coalesce("new", "vec").alias("vec"))
    gathered = pulls.df.join(held, "src")
    if open_blocks is None:
        return select_by_key(gathered, ["dst"], stage.width, {"again": (stage.marker.how, None)}), pulls.n, pulls.df
    part = gathered.join(small(open_blocks.df, open_blocks.n), "dst").select("dst", "blk", F.slice("vec", F.col("blk") * BLOCK + 1, BLOCK).alias("vec"))
    blocks = part.groupBy("dst", "blk").agg(*((F.min if stage.marker.how == "min" else F.max)(F.get("vec", F.lit(i))).alias(f"p{i}") for i in range(BLOCK)))
    return blocks.select("dst", F.col("blk"), F.array(*(F.col(f"p{i}") for i in range(BLOCK))).alias("again")), pulls.n, pulls.df


def _splice(rows: DataFrame, blocks: DataFrame, width: int) -> DataFrame:
    """Puts recomputed blocks into the incrementally updated vectors; a block without neighbours is all null."""
    by = blocks.groupBy("dst").agg(F.map_from_entries(F.collect_list(F.struct("blk", "again"))).alias("parts"))
    n = -(-width // BLOCK)
    pieces = [F.slice(F.coalesce(F.element_at("parts", F.lit(b)), F.slice("new", b * BLOCK + 1, BLOCK)), 1, min(BLOCK, width - b * BLOCK)) for b in range(n)]
    merged = rows.join(by, "dst", "left")
    return merged.withColumn("new", F.when(F.col("parts").isNull(), F.col("new")).otherwise(F.concat(*pieces))).drop("parts")


def _counted(rows: Held) -> list[tuple]:
    """(condition, evolved, n) of a stage's targets."""
    if rows.table is not None:
        found: dict[tuple, int] = {}
        for key in zip(rows.table.column("condition").to_pylist(), rows.table.column("evolved").to_pylist(), strict=True):
            found[key] = found.get(key, 0) + 1
        return [(c, e, n) for (c, e), n in found.items()]
    return [tuple(r) for r in rows.df.groupBy("condition", "evolved").agg(F.count("*").alias("n")).collect()]


def advance(state: State, delta: Held, model: ModelSpec, options: Options, changed: Held | None = None, extra: dict | None = None, also: list | None = None) -> Step:
    """One batch: all stages in order, each a fixed number of jobs, then one commit; until then nothing is changed.

    ``delta`` holds net edge changes, ``changed`` first messages that are new: node_id, old, new. A stage's targets don't
    read each other's new aggregates, so all targets of a stage go through one plan together. ``extra`` and ``also`` (rows
    of further tables) are committed along.
    """
    spark, batch, edges = state.spark, state.version + 1, state.edges
    nobody = "node_id long, old array<double>, new array<double>"
    changed = changed if changed is not None else hold(spark.createDataFrame([], nobody))
    step, writes = Step(changed.df), [("edge", delta.df), *(also or [])]
    for s, stage in enumerate(model.stages()[1:], 1):
        clock = time.perf_counter()
        how, messages, aggregates = stage.marker.how, state.msg[s], state.agg[s]
        vector = 16 + 8 * stage.width
        events = seed_events(delta.df)
        if changed.n:
            ids = ids_of(changed)
            before = edges.out_of(ids)
            events = events.unionByName(frontier_events(before, edges.after(before, delta.df, ids, "src")))
        if options.dedupe:
            events = events.dropDuplicates(["dst", "op", "src", "side"])
        events = hold(events)
        # vectors: what changed is at hand, the seeds' other sources are looked up
        others = ids_of(delta, "src", changed)
        held = messages.lookup(others)
        vectors = held.selectExpr("node_id AS src", "explode(array('before', 'after')) AS side", "vec")
        if changed.n:
            vectors = vectors.unionByName(changed.df.selectExpr("node_id AS src", "inline(array(struct('before' AS side, old AS vec), struct('after' AS side, new AS vec)))"))
        attached = attach(events.df, vectors, options.share)
        targets = ids_of(events, "dst")
        old = aggregates.lookup(targets).select(F.col("node_id").alias("dst"), F.col("vec").alias("old"))
        if options.mode == "ungrouped":
            rows = fold_events(attached, old, how).withColumn("condition", F.lit("ungrouped"))
        else:
            rows = apply_incremental(classify(reduce_events(attached, how, stage.width).join(old, "dst", "left"), how), how)
        rows = hold(rows)
        step.phases[f"events_{s}"] = time.perf_counter() - clock
        clock = time.perf_counter()
        exposed, pulled = rows if options.mode == "recompute_all" else hold_equal(rows, "condition", "exposed_reset"), 0
        now = rows.df
        if exposed.n:
            blocks = hold(exposed_blocks(exposed.df, how, stage.width)) if options.recompute_scope == "block" and options.mode == "grouped" else None
            again, pulled, pulls = recompute(exposed, delta, state, s, changed, stage, blocks)
            if blocks is None:
                hit = exposed.df.select("dst", F.lit(True).alias("hit"))
                now = now.join(hit, "dst", "left").join(again, "dst", "left").withColumn("new", F.when(F.col("hit"), F.col("again")).otherwise(F.col("new"))).drop("hit", "again")
            else:
                alive = pulls.select("dst").distinct().withColumn("alive", F.lit(True))
                empty = F.array_repeat(F.lit(None).cast("double"), BLOCK)
                now = _splice(now, blocks.df.join(again, ["dst", "blk"], "left").select("dst", "blk", F.coalesce("again", empty).alias("again")), stage.width)
                now = now.join(alive, "dst", "left").withColumn("new", F.when((F.col("condition") == "exposed_reset") & F.col("alive").isNull(), F.lit(None)).otherwise(F.col("new"))).drop("alive")
        differs = ~F.col("new").eqNullSafe(F.col("old"))
        goes_on = differs | F.col("condition").isin("covered_reset", "exposed_reset") if options.propagate == "eager" else differs
        rows = hold(now.select("dst", "old", "new", "condition", differs.alias("evolved"), (goes_on if options.early_stop else F.lit(True)).alias("goes_on")))
        step.stats += [(batch, s, *x) for x in _counted(rows)]
        writes.append((f"agg_{s}", rows.df.where("evolved").select(F.col("dst").alias("node_id"), F.col("new").alias("vec"))))
        step.phases[f"recompute_{s}"] = time.perf_counter() - clock
        clock = time.perf_counter()
        touched = rows.df.where("goes_on").select(F.col("dst").alias("node_id"), F.col("new").alias("agg"), F.lit(True).alias("known"))
        if stage.self_term and changed.n:
            touched = touched.join(changed.df.select("node_id"), "node_id", "full_outer")
        user = None
        if model.hooks.emit is not None:
            user = hold(model.hooks.merged(changed.df, s))
            writes.append((f"user_{s}", user.df))
            touched = touched.join(user.df.select("node_id"), "node_id", "full_outer")
        touched = hold(touched)
        if not touched.n:
            if changed.n:
                writes.append((f"msg_{s}", changed.df.select("node_id", F.col("new").alias("vec"))))
            step.reads += [(batch, s, kind, n) for kind, n in (("aggregate", targets.n), ("seed_message", others.n), ("frontier_message", changed.n), ("recompute_message", pulled), ("event", events.n))]
            changed = hold(spark.createDataFrame([], nobody))
            step.phases[f"transform_{s}"] = time.perf_counter() - clock
            continue
        ids = ids_of(touched)
        unknown = hold_equal(touched, "known", None)
        full = touched.df.select("node_id", "agg")
        if unknown.n:
            stored = aggregates.lookup(ids_of(unknown)).withColumnRenamed("vec", "kept")
            full = touched.df.join(stored, "node_id", "left").select("node_id", F.when(F.col("known"), F.col("agg")).otherwise(F.col("kept")).alias("agg"))
        if stage.self_term:
            own = messages.lookup(ids).join(small(changed.df.select("node_id", "new"), changed.n, vector), "node_id", "left").select("node_id", F.coalesce("new", "vec").alias("own"))
            full = full.join(own, "node_id")
        if user is not None and model.hooks.apply is not None:
            earlier = state.user[s].lookup(ids)
            full = model.hooks.apply(full, earlier.join(user.df.select("node_id"), "node_id", "left_anti").unionByName(user.df.select("node_id", "vec")))
        fresh = run_tail(stage, full, model).withColumnRenamed("vec", "new")
        last = state.msg[s + 1].lookup(ids).withColumnRenamed("vec", "old")
        nxt = fresh.join(last, "node_id").select("node_id", "old", "new")
        nxt = hold(nxt.where(~F.col("new").eqNullSafe(F.col("old"))) if options.compare == "message" else nxt)
        reads = [("aggregate", targets.n), ("seed_message", others.n), ("frontier_message", changed.n), ("recompute_message", pulled), ("self_message", ids.n if stage.self_term else 0), ("stored_aggregate", unknown.n), ("next_message", ids.n), ("user_row", ids.n if user is not None else 0), ("event", events.n)]
        step.reads += [(batch, s, kind, n) for kind, n in reads]
        if changed.n:
            writes.append((f"msg_{s}", changed.df.select("node_id", F.col("new").alias("vec"))))
        changed = nxt
        step.phases[f"transform_{s}"] = time.perf_counter() - clock
    writes.append((f"msg_{model.k + 1}", changed.df.select("node_id", F.col("new").alias("vec"))))
    state.commit(writes, **(extra or {}))
    step.changed = changed.df
    return step


class IncrementalSession:
    """Holds state (with the edges) and version of one model over one streaming graph.

    ``nodes``: (node_id, vec) features; ``edges``: (src, dst) of the first snapshot. ``apply`` takes change rows
    (t, seq, op, a, b) of one batch and returns the changed outputs and the batch's statistics. A batch is committed as
    a whole or not at all. ``resume`` takes up the last committed version of a state folder.
    """

    def __init__(self, spark: SparkSession, model: ModelSpec, nodes: DataFrame, edges: DataFrame | None, *, select: str | None = None, propagate: str = "on_change", compare: str = "aggregate", recompute_scope: str = "node", empty_fill: float = 0.0, state_dir: str | None = None, buckets: int | None = None, **flags) -> None:
        if select is not None:
            from deltamp.plans.model import Select

            model = ModelSpec(model.name, tuple(Select(select) if isinstance(op, Select) else op for op in model.ops), model.width, model.hooks, empty_fill)
        elif empty_fill:
            model = ModelSpec(model.name, model.ops, model.width, model.hooks, empty_fill)
        validate(model)
        self.spark, self.model, self.nodes, self.first_edges = spark, model, nodes, edges
        self.state = State(spark, model.k, state_dir, buckets)
        self.options = Options(propagate=propagate, compare=compare, recompute_scope=recompute_scope, **flags)
        self._stats, self._reads, self.phases = [], [], []

    @classmethod
    def resume(cls, spark: SparkSession, model: ModelSpec, nodes: DataFrame, state_dir: str, **options) -> IncrementalSession:
        session = cls(spark, model, nodes, None, state_dir=state_dir, **options)
        session.state = State.load(spark, state_dir)
        return session

    @property
    def edges(self):
        return self.state.edges

    def bootstrap(self) -> IncrementalSession:
        bootstrap(self.nodes, self.first_edges, self.model, self.state)
        return self

    def apply(self, changes: DataFrame, extra: dict | None = None, also: list | None = None) -> tuple[DataFrame, DataFrame]:
        return self.apply_delta(net_delta(changes, self.edges), extra, also)

    def apply_delta(self, delta: DataFrame | Held, extra: dict | None = None, also: list | None = None) -> tuple[DataFrame, DataFrame]:
        """``delta``: net directed changes (src, dst, op). An empty one writes nothing but what is to be committed along."""
        delta = delta if isinstance(delta, Held) else hold(delta)
        if not delta.n:
            if extra or also:
                self.state.commit(also or [], **(extra or {}))
            return self.spark.createDataFrame([], "node_id long, version long, vec array<double>"), self.stats()
        return self.take(advance(self.state, delta, self.model, self.options, extra=extra, also=also))

    def take(self, step: Step) -> tuple[DataFrame, DataFrame]:
        self._stats += step.stats
        self._reads += step.reads
        self.phases.append(step.phases)
        return step.changed.select("node_id", F.lit(self.state.version).cast("long").alias("version"), F.col("new").alias("vec")), self.spark.createDataFrame(step.stats, STATS)

    def outputs(self, version: int | None = None) -> DataFrame:
        return self.state.msg[self.model.k + 1].read(version)

    def checkpoint(self, stage: int, kind: str, version: int | None = None) -> DataFrame:
        return (self.state.msg if kind == "msg" else self.state.agg)[stage].read(version)

    def stats(self) -> DataFrame:
        return self.spark.createDataFrame(self._stats, STATS)

    def reads(self) -> DataFrame:
        return self.spark.createDataFrame(self._reads, READS)

    def storage(self) -> DataFrame:
        return self.state.storage()

    def compact(self) -> None:
        self.state.compact()

    def reset(self, model: ModelSpec) -> IncrementalSession:
        """New weights: everything is computed anew on the current edges, as a new version root beside the old one."""
        validate(model)
        edges, old = cut(self.edges.now()), self.state
        release(self.model)
        self.model, self.first_edges = model, edges
        self.state = State(self.spark, model.k, f"{old.path}/reset-{old.saved}", old.buckets)
        return self.bootstrap()

    def close(self) -> None:
        """Frees the weights that the session placed."""
        release(self.model)

    def feature_change(self, features: DataFrame) -> DataFrame:
        """New features of some nodes (node_id, vec): their first messages change, and the same path brings all else up to date."""
        from deltamp.operators.features import apply_features

        return apply_features(self, features)


__all__ = ["IncrementalSession", "Options", "advance", "pick", "recompute"]
