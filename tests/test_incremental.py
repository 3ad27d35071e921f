"""Incremental results are the full pass's bits, in every checkpoint, over random and special batches."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltamp.operators import affected as A
from deltamp.operators.extras import cached_sample, choose, diff_count, extend_sample
from deltamp.operators.features import delete_nodes, insert_nodes
from deltamp.operators.full import aggregate, complete, full_infer
from deltamp.operators import incremental, minibatch, state
from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.metrics import user_lines
from deltamp.operators.state import State, cut, hold, ids_of
from deltamp.plans import model as M
from deltamp.sources import graphs as G
from deltamp.sources import temporal as T

N = 40


def _graph(spark, seed=1, links=90):
    r = random.Random(seed)
    pairs = sorted({tuple(sorted(r.sample(range(N), 2))) for _ in range(links)})
    return pairs, cut(spark.createDataFrame(pairs, "a long, b long")), cut(spark.range(N).select(F.col("id").alias("node_id")))


def _changes(spark, rows):
    return spark.createDataFrame([(i, i, op, min(a, b), max(a, b)) for i, (op, a, b) in enumerate(rows)], "t long, seq long, op string, a long, b long")


def _session(spark, model, **flags):
    pairs, df, nodes = _graph(spark)
    return pairs, IncrementalSession(spark, model, cut(G.hashed_features(nodes, model.width)), cut(T.directed(df)), buckets=2, **flags).bootstrap()


def _check(s):
    """Outputs and each stored aggregate against a full pass on the present edges."""
    edges = cut(s.edges.now())
    assert diff_count(s.outputs(), full_infer(s.nodes, edges, s.model)) == 0
    for i, stage in enumerate(s.model.stages()[1:], 1):
        want = complete(s.nodes, aggregate(edges, s.checkpoint(i, "msg"), stage)).withColumnRenamed("agg", "vec")
        assert diff_count(s.checkpoint(i, "agg"), want) == 0


@pytest.mark.parametrize(
    ("model", "flags"),
    [
        (M.gcn(2, 6), {}), (M.sage(2, 6, "max"), {"propagate": "eager"}), (M.isonet(3, 4), {"compare": "message", "dedupe": True}),
        (M.sage(2, 40), {"recompute_scope": "block", "share": False}), (M.gcn(2, 6, order="aggregate_first"), {"mode": "recompute_all", "early_stop": False}), (M.sage_by_hooks(2, 6), {}),
    ],
)
def test_identity(spark, model, flags):
    pairs, s = _session(spark, model, **flags)
    r = random.Random(3)
    for _ in range(2):
        gone = r.sample(pairs, 4)
        new = [p for p in (tuple(sorted(r.sample(range(N), 2))) for _ in range(6)) if p not in pairs]
        out, stats = s.apply(_changes(spark, [("del", *p) for p in gone] + [("add", *p) for p in new]))
        pairs = sorted(set(pairs) - set(gone) | set(new))
        assert out.count() > 0  # not vacuous
    _check(s)
    assert s.outputs().select("vec").distinct().count() > 1
    assert s.outputs(0).count() == N


def test_special_batches(spark):
    pairs, s = _session(spark, M.gcn(2, 4))
    before = cut(s.outputs())
    hub = max(range(N), key=lambda n: sum(n in p for p in pairs))
    mine = [p for p in pairs if hub in p]
    free = next((a, b) for a in range(N) for b in range(a + 1, N) if (a, b) not in pairs)
    s.apply(_changes(spark, [("add", *pairs[0]), ("del", *free), ("add", *free), ("del", *free)]))  # nets to nothing
    assert s.state.version == 0
    s.apply(_changes(spark, [("del", *p) for p in mine]))  # all in-edges of the hub
    _check(s)
    assert s.checkpoint(1, "agg").where((F.col("node_id") == hub) & F.col("vec").isNull()).count() == 1
    s.apply(_changes(spark, [("add", *p) for p in mine]))  # undo
    assert diff_count(s.outputs(), before) == 0
    was = [cut(s.outputs(v)) for v in range(s.state.version + 1)]
    assert diff_count(was[0], was[1]) > 0
    s.compact()
    for v, rows in enumerate(was):  # earlier versions stay what they were
        assert diff_count(s.outputs(v), rows) == 0
    s.apply(_changes(spark, [("del", *mine[0])]))
    _check(s)
    assert diff_count(s.outputs(2), was[2]) == 0
    s.state.forget(2)
    with pytest.raises(ValueError, match="no longer kept"):
        s.outputs(0)
    _check(s)


def test_a_failed_batch_can_be_repeated(spark, monkeypatch, tmp_path):
    """A commit that breaks off changes nothing; the batch is applied on retry, and a stored state is taken up where it was."""
    pairs, s = _session(spark, M.sage(2, 4), state_dir=f"{tmp_path}/state")
    batch = _changes(spark, [("del", *pairs[0]), ("del", *pairs[7])])
    before, save = cut(s.outputs()), State.save
    for broken in ("save", "log"):
        with monkeypatch.context() as m:
            if broken == "save":
                m.setattr(State, "save", lambda self: (_ for _ in ()).throw(OSError("lost")))
            else:
                m.setattr(incremental, "run_tail", lambda *a: (_ for _ in ()).throw(OSError("lost")))
            with pytest.raises(OSError, match="lost"):
                s.apply(batch)
        assert s.state.version == 0 and diff_count(s.outputs(), before) == 0 and s.edges.now().count() == 2 * len(pairs)
    assert State.save is save
    s.apply(batch)
    assert s.state.version == 1 and s.edges.now().count() == 2 * len(pairs) - 4
    _check(s)
    again = IncrementalSession.resume(spark, s.model, s.nodes, f"{tmp_path}/state")
    assert again.state.version == 1 and diff_count(again.outputs(), s.outputs()) == 0
    again.apply(_changes(spark, [("add", *pairs[0])]))
    _check(again)
    assert diff_count(again.outputs(0), before) == 0


def test_many_versions_are_compacted(spark, monkeypatch):
    monkeypatch.setattr(state, "COMPACT", 2)
    pairs, s = _session(spark, M.gcn(1, 4))
    before = cut(s.outputs())
    for p in pairs[:3]:
        s.apply(_changes(spark, [("del", *p)]))
    assert [b[0] for b in s.state.msg[2].bases] == [0, 2] and s.state.version == 3
    _check(s)
    assert diff_count(s.outputs(0), before) == 0


def test_a_small_batch_reads_few_buckets(spark):
    """One changed edge is looked up as literals in its buckets' folders, in states and in both layouts of the edges."""
    nodes = cut(spark.range(4000).select(F.col("id").alias("node_id")))
    ring = cut(T.directed(spark.range(4000).select(F.col("id").alias("a"), ((F.col("id") + 1) % 4000).alias("b"))))
    s = IncrementalSession(spark, M.gcn(1, 4), cut(G.hashed_features(nodes, 4)), ring, buckets=16).bootstrap()
    ids = ids_of(hold(spark.createDataFrame([(5,), (9,)], "node_id long")))
    for rows in (s.edges.out_of(ids), s.edges.into(ids), s.state.agg[1].lookup(ids)):
        read = [f for f in rows.inputFiles()]
        plan = rows._jdf.queryExecution().executedPlan().toString()
        assert "PushedFilters: [In(" in plan and "Join" not in plan and len(read) <= 16
        assert len({f.split("bucket=")[1].split("/")[0] for f in rows.where("1 = 1").select(F.input_file_name().alias("f")).distinct().toPandas()["f"]}) <= 2
    s.apply(_changes(spark, [("del", 5, 6)]))
    _check(s)


def test_ungrouped_events_go_wrong(spark):
    pairs, s = _session(spark, M.gcn(1, 4), mode="ungrouped")
    s.apply(_changes(spark, [("del", *p) for p in pairs[::2]]))
    assert diff_count(s.outputs(), full_infer(s.nodes, s.edges.now(), s.model)) > 0


def test_nodes_and_features(spark):
    pairs, s = _session(spark, M.sage(2, 4))
    ids = spark.createDataFrame([(3,), (7,)], "node_id long")
    new = cut(ids.select("node_id", F.array(*(F.lit(float(i)) for i in range(4))).alias("vec")))
    s.feature_change(new)
    s.nodes = cut(A.overlay(s.nodes, new))
    _check(s)
    fresh = cut(G.hashed_features(spark.createDataFrame([(99,)], "node_id long"), 4))
    insert_nodes(s, fresh)
    s.nodes = cut(s.nodes.unionByName(fresh))
    s.apply(_changes(spark, [("add", 3, 99), ("add", 5, 99)]))
    delete_nodes(s, ids.where("node_id = 7"))
    _check(s)


def test_hooks_touch_a_node(spark):
    """A user event of a changed message that names another node: both modes agree, and what isn't named again is remembered."""
    emit = lambda changed, stage: changed.select((F.col("node_id") % 5).alias("node_id"), F.col("node_id").alias("from"), F.col("new").alias("vec"))
    merge = lambda e: e.groupBy("node_id").agg(F.max_by("vec", "from").alias("vec")).where("node_id = 1")
    apply = lambda rows, user: rows.join(user, "node_id", "left").select("node_id", F.when(F.col("vec").isNotNull(), F.zip_with(F.coalesce("agg", F.array_repeat(F.lit(0.0), 4)), "vec", lambda a, v: a + v)).otherwise(F.col("agg")).alias("agg"))
    pairs, s = _session(spark, M.gcn(1, 4).with_hooks(emit, merge, apply))
    assert diff_count(s.outputs(), full_infer(s.nodes, s.edges.now(), s.model)) == 0
    assert diff_count(s.outputs(), full_infer(s.nodes, s.edges.now(), M.gcn(1, 4))) == 2  # node 1 alone
    mine = next(p for p in pairs if 1 in p)
    s.apply(_changes(spark, [("del", *mine)]))
    assert diff_count(s.outputs(), full_infer(s.nodes, s.edges.now(), s.model)) == 0


def test_graphsage_by_hooks_is_graphsage(spark):
    _, df, nodes = _graph(spark)
    x, e = cut(G.hashed_features(nodes, 6)), cut(T.directed(df))
    assert diff_count(full_infer(x, e, M.sage_by_hooks(2, 6)), full_infer(x, e, M.sage(2, 6))) == 0
    assert user_lines(M.sage_by_hooks) < 10


def test_areas_hold_what_changes(spark):
    pairs, s = _session(spark, M.gcn(2, 4))
    before = cut(s.edges.now())
    s.apply(_changes(spark, [("del", *pairs[5]), ("del", *pairs[20])]))
    after, delta = cut(s.edges.now()), s.edges.by["src"].log().select("src", "dst", "op")
    real = {r.node_id for r in s.outputs().join(s.outputs(0).withColumnRenamed("vec", "o"), "node_id").where("o <> vec").collect()}
    tight = {r.node_id for r in A.area(delta, before, after, 2, "tight").collect()}
    ball = {r.node_id for r in A.area(delta, before, after, 2).collect()}
    assert real <= tight <= ball and real
    out, _, fetched = A.affected_infer(s.nodes, before, after, delta, s.model)
    assert diff_count(A.overlay(s.outputs(0), out), s.outputs()) == 0 and fetched <= N


@pytest.mark.parametrize("model", [M.gcn(2, 6), M.sage(2, 6, "max"), M.isonet(3, 4, "max")])
def test_minibatches_write_no_balls(spark, monkeypatch, model):
    """Nodes without links, and hubs that are in every ball: results and reads of the joins, but rows of the roots alone are written."""
    _, df, _ = _graph(spark)
    nodes = cut(spark.range(N + 2).select(F.col("id").alias("node_id")))
    edges = cut(T.directed(df.unionByName(spark.range(N - 1).select(F.col("id").alias("a"), F.lit(N - 1).cast("long").alias("b")))).distinct())
    features, rows = cut(G.hashed_features(nodes, model.width)), []

    def counted(x):
        rows.append((out := cut(x)).count())
        return out

    want = full_infer(features, edges, model)
    monkeypatch.setattr(minibatch, "cut", counted)
    out, reads = minibatch.minibatch_infer(nodes, features, edges, model, 4)
    assert diff_count(out.select("node_id", "vec"), want) == 0
    assert rows == [N + 2] and reads > 5 * N
    monkeypatch.setattr(minibatch, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(minibatch, "WAVE_ROWS", 6 * N)
    joined, again = minibatch.minibatch_infer(nodes, features, edges, model, 4)
    assert diff_count(joined, out) == 0 and again == reads


def test_minibatch_aggregates_in_pieces(monkeypatch):
    g = minibatch.Loaded(np.arange(4), np.zeros((4, 1)), np.array([0, 5, 5, 6, 9]), np.array([0, 1, 2, 3, 1, 2, 3, 0, 1], np.int32))
    messages = np.array([[4.0, 9.0], [np.nan, 1.0], [7.0, 2.0], [5.0, np.nan]])
    for step in (1, 2, 3, 100):
        got = [(at.tolist(), part.tolist()) for part, at, _ in g.pieces(np.array([0, 2, 3]), step)]
        assert sum((p for _, p in got), []) == g.src.tolist()
    cases = (("min", [[4, 1], [0, 0], [7, 2], [4, 1]]), ("max", [[np.nan, np.nan], [0, 0], [7, 2], [np.nan, np.nan]]))
    for (how, want), size in itertools.product(cases, (1, 4, 6, 200)):
        monkeypatch.setattr(minibatch, "PIECE", size)
        np.testing.assert_array_equal(g.aggregate(np.arange(4), messages, how, 0.0), np.array(want, float))


def test_rejected_ops():
    for ops, name in (((M.Select("mean"),), "select mean"), ((M.Unsupported("batch norm"), M.Select()), "batch norm"), ((M.Attention(None, None),), "attention")):
        with pytest.raises(M.NotIncremental, match=name):
            M.validate(M.ModelSpec("x", ops, 4))
    assert [len(s.tail) for s in M.gcn(2, 4).stages()] == [1, 3, 2]


def test_sample_and_choice(spark):
    edges = spark.createDataFrame([(s, 0) for s in range(30)] + [(s, 1) for s in range(3)], "src long, dst long")
    plain, salted = (cached_sample(edges, 5, salts=n).where("kept").groupBy("dst").count().collect() for n in (1, 4))
    assert sorted(plain) == sorted(salted) and {r.dst: r["count"] for r in plain} == {0: 5, 1: 3}
    delta = spark.createDataFrame([(40, 0, "add"), (0, 1, "del")], "src long, dst long, op string")
    after = extend_sample(cached_sample(edges, 5), delta).where("kept")
    assert after.where("dst = 0").count() == 6 and after.where("dst = 1").count() == 2
    assert choose(10, 1000, 0.1) == "incremental" and choose(900, 1000, 0.1) == "full"


def test_plan_has_no_product_and_combines_early(spark):
    _, df, nodes = _graph(spark)
    plan = full_infer(G.hashed_features(nodes, 4), T.directed(df), M.gcn(1, 4))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "partial_min" in plan and "Window" not in plan
