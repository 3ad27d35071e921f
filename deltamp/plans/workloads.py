"""The experiment workloads as reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.operators import affected as A
from deltamp.operators import metrics as C
from deltamp.operators.extras import diff_count
from deltamp.operators.full import full_infer
from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.state import cut
from deltamp.plans import model as M
from deltamp.plans.runs import Run, make_model, stream
from deltamp.sources import temporal as T

COMPARISON = "graph string, model string, n_updates int, full_s double, affected_s double, incremental_s double, incremental_p95_s double, speedup double, n_area long, n_real long, n_visited long, updatable double, feature_reads long, saved_reads long, read_ratio double, identical boolean"
HOW = {"gcn": (2, "min"), "sage": (2, "min"), "isonet": (5, "max")}


def compare(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("user_item",), kinds: tuple[str, ...] = ("gcn", "sage", "isonet"), updates: tuple[int, ...] = (1, 10, 100), d: int = 8, batches: int = 2, check: bool = True) -> DataFrame:
    """One row for each graph, model and number of updates."""
    rows = []
    for graph in graphs:
        for kind in kinds:
            k, how = HOW[kind]
            for n in updates:
                s = stream(spark, sf_dir, graph, n * batches)
                model, features = make_model(kind, k, d, how), s.features(d)
                session = IncrementalSession(spark, model, features, s.before).bootstrap()
                numbered, before, times = T.batches(s.changes, n), s.before, []
                n_area = fetched = 0
                for b in range(batches):  # every interval by all methods, on the same evaluated inputs
                    delta = T.net_delta(numbered.where(F.col("batch") == b), session.edges)
                    mine = C.timed(lambda delta=delta: session.apply_delta(delta))
                    after, out = cut(session.edges.now()), []
                    theirs = C.timed(lambda x=before, y=after, delta=delta, out=out: out.append(A.affected_infer(features, x, y, delta.df, model)))
                    whole = C.timed(lambda y=after: C.to_noop(full_infer(features, y, model)))
                    times.append((mine, theirs, whole))
                    n_area, fetched, before = n_area + out[0][1].count(), fetched + out[0][2], after
                mine, theirs, whole = zip(*times, strict=True)
                stats = {r.condition: r.n for r in C.condition_shares(session.stats()).collect()}
                visited = sum(stats.values())
                real = session.outputs(0).join(session.outputs().withColumnRenamed("vec", "now"), "node_id").where("vec <> now").count()
                reads = C.incremental_reads(session.reads())
                (mid, late), (other, _), (full_s, _) = C.spread_of(list(mine)), C.spread_of(list(theirs)), C.spread_of(list(whole))
                same = diff_count(session.outputs(), full_infer(features, before, model)) == 0 if check else None
                rows.append((graph, kind, n, full_s, other, mid, late, other / mid, n_area, real, visited, 1 - stats.get("exposed_reset", 0) / max(1, visited), fetched, reads, fetched / max(1, reads), same))
    return spark.createDataFrame(rows, COMPARISON)


def area_by_hops(spark: SparkSession, sf_dir: str, graph: str, hops: tuple[int, ...] = (1, 2, 3, 4, 5), updates: tuple[int, ...] = (1, 10, 100)) -> DataFrame:
    """Theoretical area over all nodes by number of hops and updates."""
    rows = []
    for n in updates:
        s = stream(spark, sf_dir, graph, n)
        found = cut(A.area(s.delta, s.before, s.after, max(hops)))
        counts = {r.hop: r.n for r in found.groupBy("hop").agg(F.count("*").alias("n")).collect()}  # a row for each hop
        total = s.nodes.count()
        rows += [(graph, n, k, sum(c for h, c in counts.items() if h <= k) / total) for k in hops]
    return spark.createDataFrame(rows, "graph string, n_updates int, k int, ratio double")


def phases(spark: SparkSession, sf_dir: str, graph: str, kind: str = "gcn", n: int = 10, d: int = 8) -> DataFrame:
    """Seconds by phase of a batch."""
    k, how = HOW[kind]
    run = Run(stream(spark, sf_dir, graph, n), kind, k, d, how, n)
    return spark.createDataFrame([(p.split("_")[0], int(p.split("_")[1]), float(t)) for batch in (run.session.phases) for p, t in batch.items()], "phase string, stage int, seconds double")


def baseline_phases(spark: SparkSession, sf_dir: str, graph: str, kind: str = "gcn", n: int = 10, d: int = 8) -> DataFrame:
    """Seconds of affected-area inference: finding the area and what it needs, fetching features, inference itself."""
    k, how = HOW[kind]
    s, model, held = stream(spark, sf_dir, graph, n), make_model(kind, k, d, how), {}
    features, before, after, delta = s.features(d), s.before, s.after, s.delta

    def construct() -> None:
        held["area"] = A.area(delta, before, after, model.k, "tight")
        held["need"] = A.need_sets(held["area"], after, model)

    seconds = [("construction", C.timed(construct)), ("fetch", C.timed(lambda: cut(features.join(held["need"][0], "node_id", "left_semi"))))]
    whole = C.timed(lambda: A.infer_for(held["area"], features, after, model))
    seconds.append(("inference", max(0.0, whole - seconds[1][1])))
    return spark.createDataFrame([(f"affected {p}", 0, float(t)) for p, t in seconds], "phase string, stage int, seconds double")


def grouping_ablation(spark: SparkSession, sf_dir: str, graph: str = "user_item", n: int = 20, d: int = 8) -> DataFrame:
    """Per-event recompute, ungrouped and grouped events: differing rows, reads and seconds."""
    s, rows = stream(spark, sf_dir, graph, n), []
    truth = cut(full_infer(s.features(d), s.after, make_model("gcn", 2, d, "min")))
    for mode in ("recompute_all", "ungrouped", "grouped"):
        run = Run(s, "gcn", 2, d, "min", n, (("mode", mode),))
        session = run.session
        rows.append((mode, diff_count(session.outputs(), truth), C.incremental_reads(session.reads()), sum(run.seconds)))
    return spark.createDataFrame(rows, "mode string, n_diff long, n_reads long, seconds double")


def code_size() -> dict[str, int]:
    """Of the models' source, which is no table, so this is no registered query."""
    return {k: C.user_lines(f) for k, f in {**M.ZOO, "sage_by_hooks": M.sage_by_hooks}.items()}
