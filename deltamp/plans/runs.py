"""Runs of the experiment workloads, shared by the parts of a query that look at the same run."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.operators.full import full_infer
from deltamp.operators.incremental import IncrementalSession
from deltamp.operators.state import cut
from deltamp.plans import model as M
from deltamp.sources import graphs as G
from deltamp.sources import temporal as T


def make_model(kind: str, k: int, d: int, how: str) -> M.ModelSpec:
    if kind.startswith("gcn"):
        return M.gcn(k, d, how, order="aggregate_first" if kind == "gcn_aggfirst" else "transform_first")
    return {**M.ZOO, "sage_by_hooks": M.sage_by_hooks}[kind](k, d, how)


@dataclass
class Stream:
    """A graph cut into a first snapshot and numbered held-out changes."""

    spark: SparkSession
    sf_dir: str
    graph: str
    held: int
    kept: dict = field(default_factory=dict)

    @cached_property
    def log(self) -> DataFrame:
        return cut(G.GRAPHS[self.graph](self.spark, self.sf_dir))

    @cached_property
    def changes(self) -> DataFrame:
        return cut(T.newest(self.log, self.held))

    @cached_property
    def old(self) -> T.LogEdges:
        """``before`` for lookups of few nodes."""
        return T.LogEdges(T.without(self.log, self.changes))

    @cached_property
    def new(self) -> T.LogEdges:
        """``after`` for lookups of few nodes."""
        return T.LogEdges(self.log)

    @cached_property
    def before(self) -> DataFrame:
        return cut(T.snapshot(self.old.log))

    @cached_property
    def after(self) -> DataFrame:
        return cut(T.snapshot(self.log))

    @cached_property
    def nodes(self) -> DataFrame:
        return cut(G.nodes_of(self.log))

    @cached_property
    def delta(self) -> DataFrame:
        return T.net_delta(self.changes, self.old).df

    def features(self, d: int) -> DataFrame:
        if d not in self.kept:
            self.kept[d] = cut(G.hashed_features(self.nodes, d))
        return self.kept[d]


@dataclass
class Run:
    stream: Stream
    kind: str = "gcn"
    k: int = 2
    d: int = 8
    how: str = "min"
    batch: int = 10
    options: tuple = ()

    @cached_property
    def model(self) -> M.ModelSpec:
        return make_model(self.kind, self.k, self.d, self.how)

    @cached_property
    def booted(self) -> IncrementalSession:
        """The session before the first batch."""
        s = self.stream
        return IncrementalSession(s.spark, self.model, s.features(self.d), s.before, **dict(self.options)).bootstrap()

    @cached_property
    def session(self) -> IncrementalSession:
        """The session after all batches; ``seconds`` holds each batch's time."""
        s = self.stream
        session = IncrementalSession(s.spark, self.model, s.features(self.d), s.before, **dict(self.options))
        clock = time.perf_counter()
        session.bootstrap()
        self.boot_seconds, self.seconds = time.perf_counter() - clock, []
        numbered = T.batches(s.changes, self.batch)
        for b in range(-(-s.held // self.batch)):
            clock = time.perf_counter()
            session.apply(numbered.where(F.col("batch") == b))
            self.seconds.append(time.perf_counter() - clock)
        return session

    def full(self) -> DataFrame:
        return full_infer(self.stream.features(self.d), self.stream.after, self.model)


_kept: ContextVar[dict | None] = ContextVar("kept", default=None)


@contextmanager
def apart() -> Iterator[None]:
    """Streams and runs are shared within the block and with nothing outside: each query reads its tables itself, as they are then."""
    token = _kept.set({})
    try:
        yield
    finally:
        _kept.reset(token)


def _shared(key: tuple, make: Callable):
    kept = _kept.get()
    if kept is None:
        return make()
    if key not in kept:
        kept[key] = make()
    return kept[key]


def stream(spark: SparkSession, sf_dir: str, graph: str, held: int = 20) -> Stream:
    return _shared((sf_dir, graph, held), lambda: Stream(spark, sf_dir, graph, held))


def run(spark: SparkSession, sf_dir: str, graph: str, kind: str = "gcn", k: int = 2, d: int = 8, how: str = "min", held: int = 20, batch: int = 10, **options) -> Run:
    chosen = tuple(sorted(options.items()))
    return _shared((sf_dir, graph, kind, k, d, how, held, batch, chosen), lambda: Run(stream(spark, sf_dir, graph, held), kind, k, d, how, batch, chosen))
