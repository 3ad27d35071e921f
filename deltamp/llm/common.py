"""Helpers that several training-data operators share."""

from __future__ import annotations

import tempfile
import uuid
import warnings

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that this many bytes of broadcast may hold at most; beyond it a join is shuffled.
BROADCAST_BYTES = 64 << 20


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder named by ``spark.checkpoint.dir``; a temporary one only where none is set, which suits local runs alone."""
    jsc = spark.sparkContext._jsc.sc()
    have = jsc.getCheckpointDir()
    if have.isDefined():
        return have.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        warnings.warn("spark.checkpoint.dir is not set: the temporary folder of the driver must be shared by all executors", stacklevel=2)
    spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt-"))
    return jsc.getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """The same rows, kept in the shared checkpoint folder, so a lost executor costs no replay."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


class Scratch:
    """Tables of one run, written as Parquet below the shared folder; each is deleted by name once nothing reads it any more."""

    def __init__(self, spark: SparkSession, name: str) -> None:
        self.spark, self.path, self.n = spark, f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}", 0
        self.paths: list[tuple[DataFrame, str]] = []

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.path}/{self.n}"
        df.write.parquet(path)
        kept = self.spark.read.schema(df.schema).parquet(path)
        self.paths.append((kept, path))
        return kept

    def drop(self, *tables: DataFrame | None) -> None:
        jvm = self.spark.sparkContext._jvm
        for kept, path in [(k, p) for k, p in self.paths if any(k is t for t in tables)]:
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
            self.paths.remove((kept, path))


#: A key is hot if it has more than one in ``PARTS`` of a table's rows, and more than ``FEW``.
PARTS, FEW = 2000, 64


def hot_keys(counts: DataFrame, key: str, total: int) -> DataFrame | None:
    """(key, _salts) of the hot keys among ``counts`` (key, rows): at most ``PARTS`` rows, whatever the table's size."""
    most = max(FEW, total / PARTS)
    if total <= most:
        return None
    rows = counts.where(F.col("rows") > F.lit(most)).select(key, F.ceil(F.col("rows") / F.lit(most)).cast("long").alias("_salts"))
    found = rows.collect()
    return counts.sparkSession.createDataFrame(found, rows.schema) if found else None


def dealt(left: DataFrame, right: DataFrame, key: str, hot: DataFrame | None, spread: str, how: str = "inner") -> DataFrame:
    """``left`` joined with ``right`` (unique by key). Rows of a hot key are dealt over salts by ``spread``, the other side's one row is repeated for each."""
    if hot is None:
        return left.join(right, key, how)
    salts = F.coalesce("_salts", F.lit(1).cast("long"))
    many = left.join(F.broadcast(hot), key, "left").withColumn("_salt", F.pmod(F.xxhash64(spread), salts)).drop("_salts")
    one = right.join(F.broadcast(hot), key, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), salts - 1))).drop("_salts")
    return many.join(one, [key, "_salt"], how).drop("_salt")


def free(columns: list[str], name: str) -> str:
    """``name``, with more underscores if a column is called so."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def remainder(column: str, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``: the split into folds."""
    return F.crc32(F.col(column).cast("string")) % F.lit(modulus)


def semi_by_id(big: DataFrame, ids: DataFrame, key: str, count: int) -> DataFrame:
    """Rows of ``big`` whose key is among ``ids`` (distinct); ids are broadcast only below the size bound."""
    side = F.broadcast(ids) if count * 16 <= BROADCAST_BYTES else ids
    return big.join(side, key, "left_semi")
