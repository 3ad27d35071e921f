"""Registered queries read their tables themselves, whatever ran before them in the session."""

import shutil

import pytest

from deltamp.operators.state import Ids
from deltamp.plans import queries, workloads
from deltamp.sources import graphs as G
from deltamp.sources import temporal as T

SF = "/root/testdata/sf0.001"
READS = {
    "area_source_ball_k2": {"orders", "lineitem"},
    "area_tight_k2": {"orders", "lineitem"},
    "gcn_aggfirst_full": {"events"},
    "gcn_full": {"events"},
    "gcn_full_max": {"events"},
    "iso_full": {"events"},
    "link_scores_topk": {"events"},
    "mean_full": {"events"},
    "memory_access_affected": {"orders", "lineitem"},
    "net_delta_add": {"events"},
    "report_rollup": {"events"},
}


@pytest.fixture(scope="module")
def earlier(spark):
    """Queries of the same graphs, run before."""
    for name in ("update_batches", "area_source_ball_k1"):
        queries.QUERIES[name](spark, SF).count()


@pytest.mark.parametrize("name", READS)
def test_reads_its_tables(spark, monkeypatch, earlier, name):
    read, tables = G._read, []
    monkeypatch.setattr(G, "_read", lambda s, d, table: tables.append(table) or read(s, d, table))
    assert queries.QUERIES[name](spark, SF).count() > 0
    assert set(tables) == READS[name]
    assert len(tables) == len(READS[name])  # parts of one query share what they read


def test_changed_table(spark, tmp_path):
    shutil.copytree(SF, at := tmp_path / "in")
    whole = {(r.side, r.op): r.n for r in queries.QUERIES["report_rollup"](spark, str(at)).collect()}
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.where("event_id % 2 = 0").write.parquet(str(at / "half"))
    (at / "events.parquet").chmod(0o644)
    shutil.copy(next((at / "half").glob("part-*.parquet")), at / "events.parquet")
    half = {(r.side, r.op): r.n for r in queries.QUERIES["report_rollup"](spark, str(at)).collect()}
    assert 0 < half[None, None] < whole[None, None]


def test_code_size_is_no_query():
    assert "code_size" not in queries.QUERIES
    assert workloads.code_size()["sage_by_hooks"] < 10
    assert set(workloads.code_size()) == {"gcn", "sage", "isonet", "sage_by_hooks"}


ROWS = {"events": 1_000, "orders": 1_500, "lineitem": 6_000}


def _records_read(spark) -> int:
    """Rows that tasks have read from files so far. Parquet's vectored reads of local files are missing in the bytes, not in the rows."""
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty(30_000)
    stages = sc.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None).iterator()
    total = 0
    while stages.hasNext():
        total += stages.next().inputRecords()
    return total


@pytest.mark.parametrize("name", READS)
def test_tasks_read_each_row_once(spark, earlier, name):
    before = _records_read(spark)
    queries.QUERIES[name](spark, SF).write.format("noop").mode("overwrite").save()
    assert _records_read(spark) - before == sum(ROWS[t] for t in READS[name])


@pytest.mark.parametrize("name", ["area_tight_k2", "memory_access_affected"])
def test_few_nodes_write_no_snapshot(spark, monkeypatch, name):
    monkeypatch.setattr(T, "snapshot", lambda log: pytest.fail("the whole snapshot is made"))
    assert queries.QUERIES[name](spark, SF).count() > 0


@pytest.mark.parametrize("bound", [64 << 20, 0])
def test_log_edges(spark, monkeypatch, bound):
    """Lookups, of nodes within the broadcast bound or not, give the snapshot's edges of the nodes, whatever became of a pair."""
    monkeypatch.setattr(T, "BROADCAST_BYTES", bound)
    log = spark.createDataFrame([(1, "add", 1, 2), (2, "del", 1, 2), (3, "add", 1, 2), (1, "add", 1, 3), (2, "del", 1, 3), (1, "add", 2, 3), (1, "add", 3, 4), (1, "add", 4, 5), (1, "del", 2, 9)], "t long, op string, a long, b long")
    edges = T.LogEdges(log)
    for nodes in ([], [1], [1, 2], [3, 9], [4, 77], [1, 2, 3, 4, 5, 9]):
        ids = Ids(spark.createDataFrame([(n,) for n in nodes], "node_id long"), len(nodes))
        whole = [tuple(r) for r in T.snapshot(log).collect()]
        assert sorted(tuple(r) for r in edges.out_of(ids).collect()) == sorted(e for e in whole if e[0] in nodes)
        assert sorted((r.src, r.dst) for r in edges.into(ids).collect()) == sorted(e for e in whole if e[1] in nodes)


def test_log_before_its_newest_changes(spark):
    log = spark.createDataFrame([(1, "add", 1, 2), (2, "add", 1, 3), (2, "add", 2, 3), (2, "del", 1, 4)], "t long, op string, a long, b long")
    last = T.newest(log, 2)
    assert [(r.a, r.b, r.seq) for r in last.orderBy("seq").collect()] == [(1, 4, 0), (2, 3, 1)]
    assert sorted((r.a, r.b) for r in T.without(log, last).collect()) == [(1, 2), (1, 3)]
