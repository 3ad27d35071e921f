import datetime as dt

from pyspark.sql import functions as F

from deltamp.operators.extras import diff_count
from deltamp.operators.full import full_infer
from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.state import cut
from deltamp.plans import model as M
from deltamp.sources import graphs as G
from deltamp.streaming.driver import EVENTS, StreamRunner, changes_of, sessions, windowed_counts
from deltamp.streaming.stateful import OUT, keep_aggregates


def _events(spark, rows):
    t0 = dt.datetime(2024, 1, 1)
    return spark.createDataFrame([(i, t0 + dt.timedelta(hours=h), u, kind, 0.0, f'{{"k": {k}}}') for i, h, u, k, kind in rows], EVENTS)


def test_redelivered_and_late(spark):
    nodes = cut(G.hashed_features(spark.createDataFrame([(u * 4,) for u in range(3)] + [(k * 4 + 1,) for k in range(3)], "node_id long"), 4))
    none = cut(spark.createDataFrame([], "src long, dst long"))
    s = IncrementalSession(spark, M.gcn(1, 4), nodes, none, buckets=2).bootstrap()
    runner = StreamRunner(s, cut(spark.createDataFrame([], "a long, b long, t timestamp")))
    first = _events(spark, [(1, 5, 0, 1, "view"), (2, 6, 1, 1, "view"), (3, 7, 2, 2, "click")])
    runner(first, 0)
    version = s.state.version
    runner(first, 0)  # the same batch again
    assert s.state.version == version
    runner(_events(spark, [(4, 1, 0, 1, "error"), (5, 9, 1, 1, "error")]), 1)  # the first is older than what the pair has seen
    assert {(r.src, r.dst) for r in s.edges.now().collect()} == {(0, 5), (5, 0), (8, 9), (9, 8)}
    assert diff_count(s.outputs(), full_infer(nodes, s.edges.now(), s.model)) == 0
    again = IncrementalSession.resume(spark, s.model, nodes, s.state.path)  # a new process takes up the stored state
    restarted = StreamRunner(again)
    restarted(first, 0)
    assert restarted.done == 1 and again.state.version == s.state.version
    restarted(_events(spark, [(6, 8, 1, 1, "view"), (7, 11, 0, 2, "view")]), 2)  # the first is older than the pair's last event
    assert {(r.src, r.dst) for r in again.edges.now().collect()} == {(0, 5), (5, 0), (8, 9), (9, 8), (0, 9), (9, 0)}
    assert changes_of(first).count() == 3
    assert windowed_counts(first).agg(F.sum("n")).first()[0] == 3 and sessions(first).count() == 3


def test_state_of_messages(spark, tmp_path):
    rows = [[(1, 10, "add", [3.0, 1.0]), (1, 11, "add", [2.0, 5.0])], [(1, 11, "del", [2.0, 5.0])]]
    schema = "dst long, src long, op string, vec array<double>"
    for i, part in enumerate(rows):
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in/part={i}")
    read = spark.readStream.schema(schema + ", part int").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in").select("dst", "src", "op", "vec")
    q = keep_aggregates(read).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    got = [r.vec for r in spark.read.schema(OUT).parquet(f"{tmp_path}/out").collect()]
    assert [2.0, 1.0] in got and [3.0, 1.0] in got
