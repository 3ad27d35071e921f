"""Versioned state: base tables in buckets, one log of changed rows for each version, and a manifest that commits them together."""

from __future__ import annotations

import json
import tempfile
import uuid
import warnings
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes that a broadcast side may have; ids beyond that are joined by shuffle.
BROADCAST_BYTES = 64 << 20
#: Rows up to which an intermediate result is held by the driver, as literals of the plans that read it; more are checkpointed.
SMALL = 1000
#: Buckets up to which the rows of few ids are read by one task.
FEW_BUCKETS = 8
#: Rows of a bucket that are aimed at, and buckets at least and at most.
BUCKET_ROWS, BUCKETS = 50_000, (8, 8192)
#: Versions after which a new base is written.
COMPACT = 32
LOG = "name string, node_id long, vec array<double>, src long, dst long, op string, t timestamp"


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; a temporary one only where none is set, which suits local runs alone."""
    jsc = spark.sparkContext._jsc.sc()
    if not jsc.getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not spark.sparkContext.master.startswith("local"):
            warnings.warn("spark.checkpoint.dir is not set: the temporary folder of the driver must be shared by all executors", stacklevel=2)
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt-"))
    return jsc.getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """The same rows from the shared checkpoint folder, without lineage."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def small(ids: DataFrame, count: int, row_bytes: int = 16) -> DataFrame:
    """Marked for broadcast if its size is within the bound, else left to a shuffled join."""
    return F.broadcast(ids) if count * row_bytes <= BROADCAST_BYTES else ids


@dataclass
class Held:
    """An evaluated result: its rows, their number, and the rows themselves if they are few."""

    df: DataFrame
    n: int
    table: pa.Table | None = None


def hold(df: DataFrame) -> Held:
    """Evaluates ``df`` once: few rows are kept as literals, which costs no file and no further job, others in the shared folder."""
    few = df.limit(SMALL + 1).toArrow()
    if few.num_rows <= SMALL:
        return literal(few, df)
    kept = cut(df)
    return Held(kept, kept.count())


def literal(rows: pa.Table, like: DataFrame) -> Held:
    """Few rows, with the columns of ``like``, in one partition: what groups or joins them with others in one needs no exchange."""
    return Held(like.sparkSession.createDataFrame(rows, like.schema).coalesce(1), rows.num_rows, rows)


def hold_equal(rows: Held, column: str, value: str | None) -> Held:
    """The rows that have a value (None: null) in a column; of rows held by the driver they are found without a job."""
    if rows.table is None:
        return hold(rows.df.where(F.col(column).eqNullSafe(F.lit(value))))
    found = rows.table.column(column)
    hit = rows.table.filter(pc.is_null(found) if value is None else pc.equal(found, value))
    return literal(hit if hit.num_rows else rows.table.schema.empty_table(), rows.df)


@dataclass
class Ids:
    """Distinct ids (node_id), their number, and their values if they are few."""

    df: DataFrame
    n: int
    values: list[int] | None = None

    def among(self, column: str) -> str:
        """SQL that admits the few ids."""
        return f"{column} IN ({', '.join(map(str, self.values))})" if self.values else "false"


def ids_of(rows: Held, column: str = "node_id", without: Held | None = None) -> Ids:
    """Distinct ids in a column, less those in ``without`` (node_id)."""
    spark = rows.df.sparkSession
    if rows.table is not None and (without is None or without.table is not None):
        found = np.unique(rows.table.column(column).to_numpy())
        if without is not None:
            found = np.setdiff1d(found, without.table.column("node_id").to_numpy())
        return Ids(spark.createDataFrame(pa.table({"node_id": pa.array(found, pa.int64())}), "node_id long").coalesce(1), len(found), found.tolist())
    found = rows.df.select(F.col(column).alias("node_id")).distinct()
    held = hold(found if without is None else found.join(without.df.select("node_id"), "node_id", "left_anti"))
    return Ids(held.df, held.n, held.table.column("node_id").to_pylist() if held.table is not None else None)


def bucket_of(ids, buckets: int):
    """The bucket of an id, the same for a column and for a number: few ids prune a scan without a job that looks for buckets."""
    low = F.pmod(ids, F.lit(1048576)) if isinstance(ids, Column) else ids % 1048576
    return low * 40503 % 65521 % buckets


class Table:
    """Rows by a key column: bases, each split into bucket folders and sorted by key, and the log rows of later versions.

    A reader of version v takes the newest base up to v and the log rows between; a new base leaves the older ones in
    place, so reads as of earlier versions stay what they were until ``State.forget``.
    """

    def __init__(self, state: State, name: str, key: str = "node_id", schema: str = "node_id long, vec array<double>") -> None:
        self.state, self.name, self.key, self.schema = state, name, key, f"{schema}, bucket int"
        self.bases: list[list[int]] = []  # (version, buckets), ascending

    def create(self, rows: DataFrame, version: int, count: int | None = None) -> None:
        self.state.frames.pop((self._path(version),), None)
        count = rows.count() if count is None else count
        buckets = self.state.buckets or min(max(count // BUCKET_ROWS, BUCKETS[0]), BUCKETS[1])
        placed = rows.withColumn("bucket", bucket_of(F.col(self.key), buckets).cast("int"))
        placed.repartition("bucket").sortWithinPartitions("bucket", self.key).write.mode("overwrite").partitionBy("bucket").parquet(self._path(version))
        self.bases.append([version, buckets])

    def _path(self, version: int) -> str:
        return f"{self.state.path}/base/{self.name}/v={version}"

    def _at(self, version: int | None) -> tuple[list[int], list[int]]:
        """The base to read and the log versions after it."""
        version = self.state.version if version is None else version
        fit = [b for b in self.bases if b[0] <= version]
        if not fit:
            raise ValueError(f"{self.name}: version {version} is no longer kept")
        return fit[-1], [v for v in self.state.versions if fit[-1][0] < v <= version]

    def base(self, version: int | None = None, ids: Ids | None = None) -> DataFrame:
        (v, buckets), _ = self._at(version)
        rows = self.state.frame((self._path(v),), lambda: self.state.spark.read.schema(self.schema).parquet(self._path(v)))
        if ids is None:
            return rows.drop("bucket")
        if ids.values is not None:
            hit = ", ".join(map(str, sorted({bucket_of(i, buckets) for i in ids.values})))
            return rows.where(f"bucket IN ({hit}) AND {ids.among(self.key)}" if hit else "false").drop("bucket")
        return rows.drop("bucket").join(small(ids.df.withColumnRenamed("node_id", self.key), ids.n), self.key, "left_semi")

    def log(self, version: int | None = None, ids: Ids | None = None) -> DataFrame | None:
        """Log rows with their version."""
        _, versions = self._at(version)
        if not versions:
            return None
        rows = self.state.log(versions).where(f"name = '{self.name.removesuffix('_in').removesuffix('_out')}'")
        if ids is None:
            return rows
        return rows.where(ids.among(self.key)) if ids.values is not None else rows.join(small(ids.df.withColumnRenamed("node_id", self.key), ids.n), self.key, "left_semi")

    def read(self, version: int | None = None, ids: Ids | None = None) -> DataFrame:
        """node_id, vec as of a version (the newest by default), of the given ids or of all."""
        base, log = self.base(version, ids).select("node_id", "vec"), self.log(version, ids)
        if log is None:
            return base
        newest = log.groupBy("node_id").agg(F.expr("max_by(vec, version) AS vec"))
        return base.join(newest.select("node_id"), "node_id", "left_anti").unionByName(newest)

    def lookup(self, ids: Ids, version: int | None = None) -> DataFrame:
        """Rows of distinct ids: few ids are literals that prune the base to buckets and row groups, more are broadcast or shuffled.

        The rows of few ids, one of each in the base and in a log, are grouped once by id, within one task if they lie in few
        buckets.
        """
        if ids.values is None:
            return self.read(version, ids)
        (_, buckets), _ = self._at(version)
        base, log = self.base(version, ids).select("node_id", "vec"), self.log(version, ids)
        rows = base if log is None else base.withColumn("version", F.lit(-1)).unionByName(log.select("node_id", "vec", "version"))
        if len({bucket_of(i, buckets) for i in ids.values}) <= FEW_BUCKETS:
            rows = rows.coalesce(1)
        return rows if log is None else rows.groupBy("node_id").agg(F.expr("max_by(vec, version) AS vec"))


class Edges:
    """Directed edges (src, dst) in two layouts, by source and by target; a batch's net changes are in the log.

    The edges of a few nodes are found in their buckets, so a batch costs what it touches and not the graph.
    """

    def __init__(self, state: State) -> None:
        self.by = {"src": Table(state, "edge_out", "src", "src long, dst long"), "dst": Table(state, "edge_in", "dst", "src long, dst long")}

    def create(self, rows: DataFrame, version: int) -> None:
        rows = cut(rows.select("src", "dst"))
        n = rows.count()
        for t in self.by.values():
            t.create(rows, version, n)

    def read(self, version: int | None = None, side: str = "src", ids: Ids | None = None) -> DataFrame:
        t = self.by[side]
        base, log = t.base(version, ids).select("src", "dst"), t.log(version, ids)
        if log is None:
            return base
        last = log.groupBy("src", "dst").agg(F.expr("max_by(op, version) AS op"))
        return base.join(last.select("src", "dst"), ["src", "dst"], "left_anti").unionByName(last.where("op = 'add'").select("src", "dst"))

    def now(self) -> DataFrame:
        return self.read()

    def out_of(self, ids: Ids) -> DataFrame:
        return self.read(None, "src", ids)

    def into(self, ids: Ids) -> DataFrame:
        return self.read(None, "dst", ids)

    @staticmethod
    def after(part: DataFrame, delta: DataFrame, ids: Ids, side: str) -> DataFrame:
        """The edges of ``ids`` (``part``, before) once the net changes (src, dst, op) are made."""
        new = delta.where("op = 'add'").select("src", "dst")
        new = new.where(ids.among(side)) if ids.values is not None else new.join(small(ids.df.withColumnRenamed("node_id", side), ids.n), side, "left_semi").select("src", "dst")
        return part.join(delta.select("src", "dst"), ["src", "dst"], "left_anti").unionByName(new)


class State:
    """Messages ``M_s`` (s = 1 .. k + 1), aggregates ``A_s`` (s = 1 .. k), user rows ``U_s`` and edges, and the version committed last.

    A batch changes nothing until ``commit``: its rows go to one log folder, and the manifest, written last, makes them
    part of the state. A batch that fails before that leaves the state as it was and may be repeated. ``load`` takes up the
    newest manifest of a folder.
    """

    def __init__(self, spark: SparkSession, k: int, path: str | None = None, buckets: int | None = None) -> None:
        self.spark, self.k, self.version, self.buckets = spark, k, -1, buckets
        self.path = path or f"{shared_dir(spark)}/state-{uuid.uuid4().hex}"
        self.msg = {s: Table(self, f"msg_{s}") for s in range(1, k + 2)}
        self.agg = {s: Table(self, f"agg_{s}") for s in range(1, k + 1)}
        self.user = {s: Table(self, f"user_{s}") for s in range(1, k + 1)}
        self.edges = Edges(self)
        self.last = Table(self, "last", "src", "src long, dst long, t timestamp")  # a stream's pairs with their last times
        self.versions: list[int] = []  # that have a log
        self.extra: dict = {}
        self.saved = 0
        self.frames: dict[tuple[str, ...], DataFrame] = {}

    def tables(self) -> list[Table]:
        return [*self.msg.values(), *self.agg.values(), *(t for t in (*self.user.values(), self.last) if t.bases), *self.edges.by.values()]

    def log(self, versions: list[int]) -> DataFrame:
        """The logs of some versions in one scan."""
        paths = tuple(f"{self.path}/log/version={v}" for v in versions)
        return self.frame(paths, lambda: self.spark.read.schema(f"{LOG}, version int").option("basePath", f"{self.path}/log").parquet(*paths))

    def frame(self, paths: tuple[str, ...], read) -> DataFrame:
        """The reader of some folders, whose files are listed once: committed folders don't change."""
        if paths not in self.frames:
            if len(self.frames) > 8 * COMPACT:
                self.frames.clear()
            self.frames[paths] = read()
        return self.frames[paths]

    def _files(self, path: str):
        """Hadoop's file system of a path, and the path in it."""
        at = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), at

    def start(self, version: int = 0) -> None:
        """Commits the bases that were just created."""
        self.version = version
        self.save()

    def commit(self, writes: list[tuple[str, DataFrame]], **extra) -> None:
        """Makes rows of tables, by name, the next version; ``extra`` goes into the manifest with it."""
        version = self.version + 1
        rows = None
        for name, df in writes:
            here = set(df.columns)
            full = df.selectExpr(f"'{name}' AS name", *(f"cast({c if c in here else 'NULL'} AS {kind}) AS {c}" for c, kind in (f.split(" ") for f in LOG.split(", ")[1:])))
            rows = full if rows is None else rows.unionByName(full)
        if rows is not None:
            self.frames = {paths: f for paths, f in self.frames.items() if f"{self.path}/log/version={version}" not in paths}
            rows.write.mode("overwrite").parquet(f"{self.path}/log/version={version}")
        before = (self.version, self.versions, self.extra)
        self.version, self.versions, self.extra = version, [*self.versions, *([version] if rows is not None else [])], {**self.extra, **extra}
        try:
            self.save()
        except BaseException:
            self.version, self.versions, self.extra = before
            raise
        if version - self.msg[1].bases[-1][0] >= COMPACT:
            self.compact()

    def manifest(self) -> dict:
        return {"version": self.version, "k": self.k, "buckets": self.buckets, "versions": self.versions, "extra": self.extra, "bases": {t.name: t.bases for t in self.tables()}}

    def save(self) -> None:
        """Writes the manifest through Hadoop's file layer and gives it its name when it is whole; it is the last step of a commit."""
        fs, draft = self._files(f"{self.path}/manifest/.draft-{uuid.uuid4().hex}")
        out = fs.create(draft, True)
        out.write(bytearray(json.dumps(self.manifest()).encode()))
        out.close()
        _, named = self._files(f"{self.path}/manifest/n={self.saved + 1:09d}.json")
        if not fs.rename(draft, named):
            raise OSError(f"{named} can't be written")
        self.saved += 1

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> State:
        """The state as the newest complete manifest of the folder tells it."""
        fs, at = cls(spark, 0, path)._files(f"{path}/manifest")
        last = max(name for x in fs.listStatus(at) if (name := x.getPath().getName()).startswith("n="))
        m = json.loads("".join(r[0] for r in spark.read.text(f"{path}/manifest/{last}").collect()))
        state = cls(spark, m["k"], path, m["buckets"])
        state.version, state.versions, state.extra, state.saved = m["version"], m["versions"], m["extra"], int(last[2:-5])
        for t in (*state.msg.values(), *state.agg.values(), *state.user.values(), state.last, *state.edges.by.values()):
            t.bases = m["bases"].get(t.name, [])
        return state

    def last_times(self, ids: Ids | None = None) -> DataFrame:
        """(src, dst, t): the last time of each pair that a stream has seen, of the given lower ends or of all."""
        base, log = self.last.base(None, ids).select("src", "dst", "t"), self.last.log(None, ids)
        rows = base if log is None else base.unionByName(log.select("src", "dst", "t"))
        return rows.groupBy("src", "dst").agg(F.max("t").alias("t"))

    def storage(self) -> DataFrame:
        """Rows and numbers that are kept: kind, stage, rows, floats."""
        out = None
        for kind, tables in (("message", self.msg), ("aggregate", self.agg)):
            for s, t in tables.items():
                floats = F.coalesce(F.sum(F.when(F.col("vec").isNotNull(), F.size("vec"))), F.lit(0)).cast("long").alias("n_floats")
                part = t.read().agg(F.count("*").alias("n_rows"), floats).select(F.lit(kind).alias("kind"), F.lit(s).alias("stage"), "n_rows", "n_floats")
                out = part if out is None else out.unionByName(part)
        return out

    def compact(self) -> None:
        """A new base of every table at the present version; earlier versions stay readable."""
        edges = self.edges.now()
        for t in (*self.msg.values(), *self.agg.values(), *(u for u in self.user.values() if u.bases)):
            if t.bases[-1][0] < self.version:
                t.create(t.read(), self.version)
        if self.edges.by["src"].bases[-1][0] < self.version:
            self.edges.create(edges, self.version)
        if self.last.bases and self.last.bases[-1][0] < self.version:
            self.last.create(self.last_times(), self.version)
        self.save()

    def forget(self, before: int) -> None:
        """Earlier versions are no longer kept: their reads raise an error, and bases and logs that nothing else needs are left out."""
        for t in self.tables():
            fit = [b for b in t.bases if b[0] <= before]
            t.bases = [*fit[-1:], *(b for b in t.bases if b[0] > before)]
        first = min(t.bases[0][0] for t in self.tables())
        self.versions = [v for v in self.versions if v > first]
        self.save()
