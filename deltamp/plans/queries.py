"""Registered queries of the inference engine, each with its DuckDB twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.functions.vectors import reset_mask, unnest
from deltamp.operators import affected as A
from deltamp.operators import extras as X
from deltamp.operators import metrics as C
from deltamp.operators import minibatch as B
from deltamp.operators.classify import classify
from deltamp.operators.events import attach, reduce_events, seed_events
from deltamp.operators.full import aggregate, complete, full_infer
from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.state import cut
from deltamp.plans import model as M
from deltamp.plans import oracle as O
from deltamp.plans.runs import apart, run, stream
from deltamp.sources import graphs as G
from deltamp.sources import temporal as T

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}
HELD, D = 20, 8
#: Held-out changes of the one-batch checks of the first stage; held-out changes and changes of a batch in the measures of a run.
HELD_OUT, MEASURED, STEP = 1000, 300, 100


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        @wraps(f)
        def alone(s: SparkSession, d: str) -> DataFrame:
            with apart():
                return f(s, d)

        QUERIES[name] = alone
        if sql:
            ORACLE[name] = sql
        return f

    return add


def _long(df: DataFrame) -> DataFrame:
    return unnest(df).select("node_id", F.col("dim").cast("int").alias("dim"), "val")


# graphs and their changes

for _name, _graph in (("user_item_edges", "user_item"), ("cust_part_edges", "cust_part"), ("part_supp_edges", "part_supp"), ("vec_edges", "vec"), ("page_link_edges", "page_link"), ("turn_edges", "turns")):
    query(_name, f"WITH {O.LOGS[_graph]}, {O.pairs('log', 'e')} SELECT src, dst FROM e")(lambda s, d, g=_graph: T.snapshot(G.GRAPHS[g](s, d)))

_AT = "1998-06-01"


@query("snapshot_edges", f"WITH {O.LOGS['cust_part']}, cut AS (SELECT * FROM log WHERE t <= TIMESTAMP '{_AT}'), {O.pairs('cut', 'e')} SELECT src, dst FROM e")
def snapshot_edges(s: SparkSession, d: str) -> DataFrame:
    return T.snapshot_at(T.intervals(G.cust_part(s, d)), F.lit(_AT).cast("timestamp"))


@query("net_delta_add", O.graph_only("user_item", HELD, "SELECT src, dst FROM delta WHERE op = 'add'"))
def net_delta_add(s: SparkSession, d: str) -> DataFrame:
    return stream(s, d, "user_item", HELD).delta.where("op = 'add'").select("src", "dst")


@query("net_delta_del", O.graph_only("cust_part", 100, "SELECT src, dst FROM delta WHERE op = 'del'"))
def net_delta_del(s: SparkSession, d: str) -> DataFrame:
    return stream(s, d, "cust_part", 100).delta.where("op = 'del'").select("src", "dst")


@query("update_batches", O.graph_only("user_item", HELD, "SELECT a, b, op, (seq // 10)::INTEGER AS batch FROM ch"))
def update_batches(s: SparkSession, d: str) -> DataFrame:
    return T.batches(stream(s, d, "user_item", HELD).changes, 10).select("a", "b", "op", "batch")


@query("latest_edges_topk", f"WITH {O.LOGS['part_supp']}, l AS (SELECT a, b, arg_max(op, t) AS op, max(t) AS t FROM log GROUP BY a, b) SELECT a, b, t FROM l WHERE op = 'add' ORDER BY t DESC, a DESC, b DESC LIMIT 250000")
def latest_edges_topk(s: SparkSession, d: str) -> DataFrame:
    return T.latest_pairs(G.part_supp(s, d))


@query("degree_onehot_idx", f"WITH {O.LOGS['part_supp']}, {O.pairs('log', 'e')}, {O.NODES} SELECT n.node_id, least(coalesce(c, 0), 500)::INTEGER AS slot FROM nodes n LEFT JOIN (SELECT dst, count(*) AS c FROM e GROUP BY dst) q ON q.dst = n.node_id")
def degree_onehot_idx(s: SparkSession, d: str) -> DataFrame:
    st = stream(s, d, "part_supp")
    return G.degree_index(st.after, st.nodes)


@query("vec_features_quantised", "SELECT vec_id AS node_id, (i - 1)::INTEGER AS dim, floor(embedding[i]::DOUBLE * 1024 + 0.5) + 1024 AS val FROM embeddings CROSS JOIN range(1, 65) r(i)")
def vec_features_quantised(s: SparkSession, d: str) -> DataFrame:
    return _long(G.vector_features(s, d))


# full passes

for _name, _kind, _k, _how in (("gcn_full", "gcn", 2, "min"), ("gcn_full_max", "gcn", 2, "max"), ("gcn_aggfirst_full", "gcn_aggfirst", 2, "min"), ("sage_full", "sage", 2, "min"), ("iso_full", "isonet", 3, "max")):
    query(_name, O.full("user_item", _kind, _k, D, _how))(lambda s, d, a=(_kind, _k, D, _how): _long(run(s, d, "user_item", *a).full()))


def _other(how: str) -> M.ModelSpec:
    """One layer with an aggregation outside the incremental class; full mode only."""
    return M.ModelSpec(how, (M.Select(how), M.Dense(M.fixed_weights(D, D)), M.Bias(M.BIAS), M.Relu()), D)


for _how, _sql in (("sum", "sum"), ("mean", "avg")):
    query(f"{_how}_full", O.full("user_item", "gcn_aggfirst", 1, D, _sql, "SELECT node_id, (i - 1)::INTEGER AS dim, round(v[i], 4) AS val FROM {last} CROSS JOIN range(1, 9) r(i)"))(
        lambda s, d, how=_how: _long(full_infer(stream(s, d, "user_item").features(D), stream(s, d, "user_item").after, _other(how))).withColumn("val", F.round("val", 4))
    )

_L, _R = [1e-6 * (i + 1) for i in range(D)], [2e-6 * (D - i) for i in range(D)]
_dot = lambda v, w: " + ".join(f"{v}[{i + 1}] * {x!r}" for i, x in enumerate(w))


@query("attention_full", f"""WITH {O.LOGS["user_item"]}, {O.pairs("log", "e")}, {O.NODES}, {O.features(D)},
z AS (SELECT src, dst, f.v, {_dot("f.v", _L)} + {_dot("g.v", _R)} AS z FROM e JOIN feat f ON src = f.node_id JOIN feat g ON dst = g.node_id),
y AS (SELECT dst, v, exp(CASE WHEN z < 0 THEN 0.2 * z ELSE z END) AS w FROM z)
SELECT dst AS node_id, (i - 1)::INTEGER AS dim, round(sum(w * v[i]) / sum(w), 4) AS val FROM y CROSS JOIN range(1, {D + 1}) r(i) GROUP BY dst, i""")
def attention_full(s: SparkSession, d: str) -> DataFrame:
    st = stream(s, d, "user_item")
    stage = M.ModelSpec("attention", (M.Attention(np.array(_L), np.array(_R)),), D).stages()[1]
    return unnest(aggregate(st.after, st.features(D), stage), "agg").select("node_id", F.col("dim").cast("int").alias("dim"), F.round("val", 4).alias("val"))


# incremental: the twin is the full pass on the final snapshot

_INCREMENTAL = (
    ("gcn_incremental", "user_item", "gcn", 2, "min", {}), ("gcn_incremental_max", "user_item", "gcn", 2, "max", {}), ("gcn_incremental_cust_part", "cust_part", "gcn", 2, "min", {}),
    ("gcn_incremental_part_supp", "part_supp", "gcn", 2, "min", {}), ("gcn_incremental_vec", "vec", "gcn", 2, "min", {}), ("gcn_incremental_page_link", "page_link", "gcn", 2, "min", {}),
    ("gcn_incremental_turns", "turns", "gcn", 2, "min", {}), ("gcn_aggfirst_incremental", "user_item", "gcn_aggfirst", 2, "min", {}), ("sage_incremental", "user_item", "sage", 2, "min", {}),
    ("sage_incremental_cust_part", "cust_part", "sage", 2, "min", {}), ("iso_incremental", "vec", "isonet", 5, "max", {}), ("iso_incremental_user_item", "user_item", "isonet", 3, "max", {}),
    ("gcn_incremental_eager", "user_item", "gcn", 2, "min", {"propagate": "eager"}), ("gcn_incremental_recompute_all", "user_item", "gcn", 2, "min", {"mode": "recompute_all"}),
    ("sage_incremental_block_scope", "user_item", "sage", 2, "min", {"recompute_scope": "block", "d": 40}), ("sage_by_hooks_incremental", "user_item", "sage_by_hooks", 2, "min", {}), ("sage_incremental_message_compare", "user_item", "sage", 2, "min", {"compare": "message", "dedupe": True, "share": False}),
)

for _name, _graph, _kind, _k, _how, _opt in _INCREMENTAL:
    _opt, _d = {k: v for k, v in _opt.items() if k != "d"}, _opt.get("d", D)  # block scope needs more than one block
    query(_name, O.full(_graph, _kind.removesuffix("_by_hooks"), _k, _d, _how))(lambda s, d, g=_graph, a=(_kind, _k, _d, _how, HELD, HELD // 2), o=_opt: _long(run(s, d, g, *a, **o).session.outputs()))


@query("gcn_checkpoints_stage1", O.full("user_item", "gcn", 2, D, "min", O.long("a1", D, "WHERE v IS NOT NULL")))
def gcn_checkpoints_stage1(s: SparkSession, d: str) -> DataFrame:
    """Every checkpoint must be identical, not outputs alone: here the first aggregates."""
    return _long(run(s, d, "user_item", held=HELD).session.checkpoint(1, "agg").where("vec IS NOT NULL"))


@query("gcn_outputs_as_of_0", f"WITH {O.LOGS['user_item']},\n{O.HELD.format(n=HELD)},\n{O.pairs('old', 'e')},\n{O.NODES},\n{O.features(D)},\n{O.forward('gcn', 2, D, 'min')[0]}\n{O.long('m3', D)}")
def gcn_outputs_as_of_0(s: SparkSession, d: str) -> DataFrame:
    return _long(run(s, d, "user_item", held=HELD).session.outputs(0))


# baselines

def _restricted(kind: str, k: int, seeds: str) -> str:
    """Full pass restricted to the tight area of the held-out changes."""
    ctes, last = O.forward(kind, k, D, "min")
    return f"WITH {O.LOGS['user_item']},\n{O.HELD.format(n=HELD)},\n{O.pairs('log', 'e')},\n{O.pairs('old', 'eb')},\n{O.NODES},\n{O.features(D)},\n{ctes},\n{O.DELTA}, {O.ball(k - 1, 'e', seeds)}\n{O.long(last, D, f'WHERE node_id IN (SELECT node_id FROM h{k - 1})')}"


for _kind in ("gcn", "sage"):
    query(f"{_kind}_affected", _restricted(_kind, 2, "SELECT DISTINCT dst AS node_id FROM delta"))(
        lambda s, d, kind=_kind: _long(A.affected_infer(stream(s, d, "user_item", HELD).features(D), stream(s, d, "user_item", HELD).before, stream(s, d, "user_item", HELD).after, stream(s, d, "user_item", HELD).delta, run(s, d, "user_item", kind, held=HELD).model)[0])
    )


@query("gcn_minibatch", O.full("user_item", "gcn", 2, D, "min", O.long("m3", D)))
def gcn_minibatch(s: SparkSession, d: str) -> DataFrame:
    """Every node is a root, in batches of about 16."""
    st = stream(s, d, "user_item", HELD)
    out, _ = B.minibatch_infer(st.nodes, st.features(D), st.after, run(s, d, "user_item", held=HELD).model)
    return _long(out.select("node_id", "vec"))


@query("iso_ego", O.full("vec", "isonet", 3, D, "max", O.long("m4", D)))
def iso_ego(s: SparkSession, d: str) -> DataFrame:
    """An ego network for each node."""
    st = stream(s, d, "vec", HELD)
    out, _ = B.ego_infer(st.nodes, st.features(D), st.after, run(s, d, "vec", "isonet", 3, D, "max", HELD).model)
    return _long(out.select("node_id", "vec"))


@query("ego_sizes", f"WITH {O.LOGS['vec']}, {O.pairs('log', 'e')}, {O.NODES}, r0 AS (SELECT node_id AS root, node_id FROM nodes), r1 AS (SELECT * FROM r0 UNION SELECT root, src FROM e JOIN r0 ON dst = node_id), r2 AS (SELECT * FROM r1 UNION SELECT root, src FROM e JOIN r1 ON dst = node_id) SELECT root, count(*) AS n FROM r2 GROUP BY root")
def ego_sizes(s: SparkSession, d: str) -> DataFrame:
    st = stream(s, d, "vec", HELD)
    return B.ego_networks(st.nodes, st.after, 2).groupBy("root").agg(F.count("*").alias("n"))


# measures

for _k in (1, 2, 3):
    query(f"area_source_ball_k{_k}", O.graph_only("cust_part", HELD, f", u AS (SELECT * FROM e UNION SELECT * FROM eb), {O.ball(_k, 'u', 'SELECT DISTINCT src AS node_id FROM delta')} SELECT node_id FROM h{_k}"))(
        lambda s, d, k=_k: A.area(stream(s, d, "cust_part", HELD).delta, stream(s, d, "cust_part", HELD).before, stream(s, d, "cust_part", HELD).after, k).select("node_id")
    )


@query("area_tight_k2", O.graph_only("cust_part", HELD, f", {O.ball(1, 'e', 'SELECT DISTINCT dst AS node_id FROM delta')} SELECT node_id FROM h1"))
def area_tight_k2(s: SparkSession, d: str) -> DataFrame:
    st = stream(s, d, "cust_part", HELD)
    return A.area(st.delta, st.old, st.new, 2, "tight").select("node_id")


@query("real_affected", O.both("cust_part", MEASURED, "gcn", 2, D, "min", "SELECT b.node_id FROM bm3 b JOIN cm3 c USING (node_id) WHERE b.v <> c.v"))
def real_affected(s: SparkSession, d: str) -> DataFrame:
    """Nodes whose output really changed between the first and the last version."""
    session = run(s, d, "cust_part", held=MEASURED, batch=STEP).session
    old, new = session.outputs(0), session.outputs()
    return old.join(new.withColumnRenamed("vec", "now"), "node_id").where("vec <> now").select("node_id")


@query("real_ratio", O.both("cust_part", MEASURED, "gcn", 2, D, "min", f", {O.ball(1, 'e', 'SELECT DISTINCT dst AS node_id FROM delta')} SELECT (SELECT count(*) FROM bm3 b JOIN cm3 c USING (node_id) WHERE b.v <> c.v) AS n_real, (SELECT count(*) FROM h1) AS n_area"))
def real_ratio(s: SparkSession, d: str) -> DataFrame:
    real = real_affected(s, d).agg(F.count("*").alias("n_real"))
    st = stream(s, d, "cust_part", MEASURED)
    return real.join(F.broadcast(A.area(st.delta, st.before, st.after, 2, "tight").agg(F.count("*").alias("n_area"))))


_SEEDS = ", ev AS (SELECT dst, op, m.v FROM delta JOIN bm1 m ON src = m.node_id)"
_GROUPED = _SEEDS + f", g AS (SELECT dst, i, min(CASE WHEN op = 'del' THEN v[i] END) AS dv, min(CASE WHEN op = 'add' THEN v[i] END) AS av FROM ev CROSS JOIN range(1, {D + 1}) r(i) GROUP BY dst, i)"


def _stage1(s: SparkSession, d: str) -> DataFrame:
    """Reduced events and old aggregates of the first stage, all held-out changes as one batch; messages there don't change."""
    st, session = stream(s, d, "cust_part", HELD_OUT), run(s, d, "cust_part", held=HELD_OUT).booted
    vectors = session.checkpoint(1, "msg", 0).select(F.col("node_id").alias("src"), F.explode(F.array(F.lit("before"), F.lit("after"))).alias("side"), "vec")
    grouped = reduce_events(attach(seed_events(st.delta), vectors), "min", D)
    return grouped.join(session.checkpoint(1, "agg", 0).select(F.col("node_id").alias("dst"), F.col("vec").alias("old")), "dst", "left")


@query("seed_events_stage1", O.graph_only("cust_part", HELD_OUT, "SELECT dst, op, src FROM delta"))
def seed_events_stage1(s: SparkSession, d: str) -> DataFrame:
    return seed_events(stream(s, d, "cust_part", HELD_OUT).delta).select("dst", "op", "src")


@query("grouped_events_stage1", O.both("cust_part", HELD_OUT, "gcn", 1, D, "min", _GROUPED + " SELECT dst, (i - 1)::INTEGER AS dim, dv AS del_val, av AS add_val FROM g"))
def grouped_events_stage1(s: SparkSession, d: str) -> DataFrame:
    one = lambda c: F.coalesce(c, F.array_repeat(F.lit(None).cast("double"), D))
    return _stage1(s, d).select("dst", F.posexplode(F.arrays_zip(one("del_vec").alias("x"), one("add_vec").alias("y"))).alias("dim", "p")).select("dst", F.col("dim").cast("int").alias("dim"), F.col("p").getField("x").alias("del_val"), F.col("p").getField("y").alias("add_val"))


@query("reset_mask_stage1", O.both("cust_part", HELD_OUT, "gcn", 1, D, "min", _GROUPED + " SELECT g.dst, (i - 1)::INTEGER AS dim, a.v[i] = dv AS reset FROM g JOIN ba1 a ON a.node_id = g.dst WHERE dv IS NOT NULL AND a.v IS NOT NULL"))
def reset_mask_stage1(s: SparkSession, d: str) -> DataFrame:
    return _stage1(s, d).where("del_vec IS NOT NULL AND old IS NOT NULL").select("dst", F.posexplode(reset_mask(F.col("old"), F.col("del_vec"))).alias("dim", "reset")).select("dst", F.col("dim").cast("int").alias("dim"), "reset")


@query("condition_counts_stage1", O.both("cust_part", HELD_OUT, "gcn", 1, D, "min", _GROUPED + """, c AS (SELECT g.dst, bool_or(dv IS NOT NULL AND a.v IS NOT NULL) AS has, bool_or(coalesce(a.v[i] = dv, false)) AS hit, bool_and(coalesce(a.v[i] <> dv, true) OR coalesce(av <= a.v[i], false)) AS cov
  FROM g JOIN ba1 a ON a.node_id = g.dst GROUP BY g.dst)
SELECT CASE WHEN NOT has THEN 'no_deletion' WHEN NOT hit THEN 'deletion_no_effect' WHEN cov THEN 'covered_reset' ELSE 'exposed_reset' END AS condition, count(*) AS n FROM c GROUP BY 1"""))
def condition_counts_stage1(s: SparkSession, d: str) -> DataFrame:
    return classify(_stage1(s, d), "min").groupBy("condition").agg(F.count("*").alias("n"))


@query("memory_access_affected", O.graph_only("cust_part", HELD, f", {O.ball(1, 'e', 'SELECT DISTINCT dst AS node_id FROM delta')}, n2 AS (SELECT DISTINCT src AS node_id FROM e JOIN h1 ON dst = node_id), n1 AS (SELECT DISTINCT src AS node_id FROM e JOIN n2 ON dst = node_id) SELECT count(*) AS n_rows FROM n1"))
def memory_access_affected(s: SparkSession, d: str) -> DataFrame:
    """Feature rows that affected-area inference fetches."""
    st = stream(s, d, "cust_part", HELD)
    inside = A.area(st.delta, st.old, st.new, 2, "tight")
    return A.need_sets(inside, st.new, run(s, d, "cust_part", held=HELD).model)[0].agg(F.count("*").alias("n_rows"))


@query("memory_access_incremental")
def memory_access_incremental(s: SparkSession, d: str) -> DataFrame:
    """C8 by kind of saved vector."""
    return run(s, d, "cust_part", held=MEASURED, batch=STEP).session.reads().groupBy("kind").agg(F.sum("n").alias("n"))


@query("storage_overhead", O.full("user_item", "gcn", 2, D, "min", f"SELECT ((SELECT count(*) FROM nodes) * 3 * {D} + (SELECT count(*) FROM a1 WHERE v IS NOT NULL) * {D} + (SELECT count(*) FROM a2 WHERE v IS NOT NULL) * {D})::BIGINT AS n_floats, ((SELECT count(*) FROM nodes) * {D} * 8 + (SELECT count(*) FROM e) * 16)::BIGINT AS data_bytes"))
def storage_overhead(s: SparkSession, d: str) -> DataFrame:
    st = stream(s, d, "user_item", HELD)
    return C.storage_overhead(run(s, d, "user_item", held=HELD).session.storage(), st.nodes.count() * D, st.after.count()).select("n_floats", "data_bytes")


@query("condition_shares")
def condition_shares(s: SparkSession, d: str) -> DataFrame:
    return C.condition_shares(run(s, d, "cust_part", held=MEASURED, batch=STEP).session.stats())


@query("report_rollup", f"WITH {O.LOGS['user_item']}, x AS (SELECT CASE WHEN a % 4 = 0 THEN 'user' ELSE 'item' END AS side, op FROM log) SELECT side, op, count(*) AS n FROM x GROUP BY ROLLUP (side, op)")
def report_rollup(s: SparkSession, d: str) -> DataFrame:
    side = F.when(F.col("a") % 4 == 0, "user").otherwise("item").alias("side")
    return stream(s, d, "user_item", HELD).log.select(side, "op").rollup("side", "op").agg(F.count("*").alias("n"))


@query("condition_rollup")
def condition_rollup(s: SparkSession, d: str) -> DataFrame:
    return C.condition_rollup(run(s, d, "user_item", held=HELD).session.stats())


# pooling, sampling, links

@query("iso_pooled_by_nation", O.full("cust_part", "isonet", 2, D, "max", "SELECT c_nationkey::BIGINT AS group_id, (i - 1)::INTEGER AS dim, sum(v[i]) AS val FROM {last} JOIN customer ON node_id = c_custkey * 4 CROSS JOIN range(1, 9) r(i) GROUP BY c_nationkey, i"))
def iso_pooled_by_nation(s: SparkSession, d: str) -> DataFrame:
    groups = s.read.parquet(f"{d}/customer.parquet").select((F.col("c_custkey") * 4).alias("node_id"), F.col("c_nationkey").cast("long").alias("group_id"))
    pooled = X.pool(run(s, d, "cust_part", "isonet", 2, D, "max", HELD).full(), groups, D, "sum")
    return unnest(pooled, key="group_id").select("group_id", F.col("dim").cast("int").alias("dim"), "val")


@query("iso_pooled_after_update", ORACLE["iso_pooled_by_nation"])
def iso_pooled_after_update(s: SparkSession, d: str) -> DataFrame:
    """The pooled outputs once the held-out changes are applied."""
    groups = s.read.parquet(f"{d}/customer.parquet").select((F.col("c_custkey") * 4).alias("node_id"), F.col("c_nationkey").cast("long").alias("group_id"))
    pooled = X.pool(run(s, d, "cust_part", "isonet", 2, D, "max", HELD).session.outputs(), groups, D, "sum")
    return unnest(pooled, key="group_id").select("group_id", F.col("dim").cast("int").alias("dim"), "val")


def _sampled_sql() -> str:
    """The first eight in-edges of a node by the pair's hash, less the deleted ones, and all inserted ones."""
    h = "(1000003 * (src % 1048576) + 7919 * (dst % 1048576) + 42) % 2147483647"
    kept = f"es AS (SELECT r.src, r.dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY {h}, src) AS n FROM eb) r LEFT JOIN delta q ON q.src = r.src AND q.dst = r.dst WHERE n <= 8 AND q.src IS NULL UNION ALL SELECT src, dst FROM delta WHERE op = 'add')"
    ctes, last = O.forward("sage", 2, D, "min", "es")
    return f"WITH {O.LOGS['part_supp']},\n{O.HELD.format(n=HELD)},\n{O.pairs('log', 'e')},\n{O.pairs('old', 'eb')},\n{O.NODES},\n{O.features(D)},\n{O.DELTA},\n{kept},\n{ctes}\n{O.long(last, D)}"


@query("sampled_sage_incremental", _sampled_sql())
def sampled_sage_incremental(s: SparkSession, d: str) -> DataFrame:
    """The incremental step on a cached sample: what it doesn't hold is not an event."""
    st, model = stream(s, d, "part_supp", HELD), run(s, d, "part_supp", "sage", held=HELD).model
    sample = cut(X.cached_sample(st.before, 8, salts=4))
    session = IncrementalSession(s, model, st.features(D), cut(sample.where("kept").select("src", "dst"))).bootstrap()
    session.apply_delta(X.sampled_delta(sample, st.delta))
    return _long(session.outputs())


@query("sampled_sage", _sampled_sql())
def sampled_sage(s: SparkSession, d: str) -> DataFrame:
    """GraphSAGE on at most eight cached in-neighbours of each node, salted for hubs; inserted edges are kept."""
    st = stream(s, d, "part_supp", HELD)
    sample = X.extend_sample(X.cached_sample(st.before, 8, salts=4), st.delta)
    return _long(full_infer(st.features(D), cut(sample.where("kept").select("src", "dst")), run(s, d, "part_supp", "sage", held=HELD).model))


@query("link_scores_topk", O.full("user_item", "gcn", 2, D, "min", f"SELECT a, b, list_dot_product(x.v, y.v) AS score FROM ep JOIN {{last}} x ON a = x.node_id JOIN {{last}} y ON b = y.node_id ORDER BY score DESC, a, b LIMIT 20"))
def link_scores_topk(s: SparkSession, d: str) -> DataFrame:
    out = cut(run(s, d, "user_item", held=HELD).full())
    pairs = stream(s, d, "user_item", HELD).after.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return X.link_scores(out, pairs).orderBy(F.desc("score"), "a", "b").limit(20)


@query("ungrouped_differs")
def ungrouped_differs(s: SparkSession, d: str) -> DataFrame:
    """B6 against B7: outputs that go wrong when events are applied one by one."""
    right = run(s, d, "user_item", held=HELD).session.outputs()
    wrong = run(s, d, "user_item", held=HELD, batch=HELD, mode="ungrouped").session.outputs()
    return right.exceptAll(wrong).agg(F.count("*").alias("n_wrong"))


@query("stream_user_item_final", O.full("user_item", "gcn", 2, D, "min"))
def stream_user_item_final(s: SparkSession, d: str) -> DataFrame:
    """The events as a file stream of a few micro-batches, read to the end."""
    from deltamp.streaming.driver import stream_user_item

    return _long(stream_user_item(s, d, M.gcn(2, D)).outputs())


@query("method_comparison")
def method_comparison(s: SparkSession, d: str) -> DataFrame:
    """Full, affected-area and incremental side by side, with the hardware-free counts."""
    from deltamp.plans.workloads import compare

    return compare(s, d, graphs=("user_item",), kinds=("gcn",), updates=(1, 10, 100))


for _graph, _kind in (("cust_part", "sage"), ("vec", "isonet")):

    @query(f"method_comparison_{_kind}_{_graph}")
    def _comparison(s: SparkSession, d: str, graph: str = _graph, kind: str = _kind) -> DataFrame:
        from deltamp.plans.workloads import compare

        return compare(s, d, graphs=(graph,), kinds=(kind,), updates=(10,))


@query("area_by_hops")
def area_by_hops(s: SparkSession, d: str) -> DataFrame:
    """Theoretical area over all nodes by hops and updates."""
    from deltamp.plans import workloads

    return workloads.area_by_hops(s, d, "part_supp")


@query("phase_breakdown")
def phase_breakdown(s: SparkSession, d: str) -> DataFrame:
    """Seconds by phase, of the incremental step and of affected-area inference."""
    from deltamp.plans import workloads

    return workloads.phases(s, d, "user_item").unionByName(workloads.baseline_phases(s, d, "user_item"))


@query("grouping_ablation")
def grouping_ablation(s: SparkSession, d: str) -> DataFrame:
    """Recompute all, ungrouped and grouped events."""
    from deltamp.plans import workloads

    return workloads.grouping_ablation(s, d)


@query("iso_onehot_identity")
def iso_onehot_identity(s: SparkSession, d: str) -> DataFrame:
    """The isomorphism network on degree one-hot features (frozen at the first snapshot): rows that differ from a full pass."""
    st = stream(s, d, "vec", HELD)
    features, model = cut(G.degree_onehot(st.before, st.nodes)), M.isonet(2, 64, "max", 501)
    session = IncrementalSession(s, model, features, st.before).bootstrap()
    session.apply_delta(st.delta)
    return C.report(s, [("isonet", X.diff_count(session.outputs(), full_infer(features, st.after, model)))], "model string, n_diff long")


__all__ = ["ORACLE", "QUERIES", "complete"]
