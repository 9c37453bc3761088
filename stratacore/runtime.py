"""Shared folders, written tables and counters for iterative methods."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; only a one-process session without it (tests) gets a temporary folder."""
    jsc = spark.sparkContext._jsc.sc()
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if jsc.getCheckpointDir().isDefined():
            return jsc.getCheckpointDir().get()
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, base, True)
    if not jsc.getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(base)
    return base


def new_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, path: str) -> None:
    """Delete a table that this package wrote."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


#: Spark's own switch for dropping the shuffle files of a finished execution; a session setting, absent before 4.1.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Executions inside leave no shuffle files behind. For tables that are written once: nothing reads those again."""
    try:
        before = spark.conf.get(CLEANUP, None)
        spark.conf.set(CLEANUP, "true")
    except Exception:  # noqa: BLE001 - a session that lacks the setting keeps its files until they are collected
        yield
        return
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, before) if before is not None else spark.conf.unset(CLEANUP)


def written(df: DataFrame, label: str, *partition_by: str) -> DataFrame:
    """Cut lineage by a Parquet table in the shared folder: a lost executor costs no recomputation, and the shuffle
    files that made it are dropped."""
    spark, path = df.sparkSession, new_path(df.sparkSession, label)
    with shuffles_dropped(spark):
        df.write.option("compression", "zstd").partitionBy(*partition_by).parquet(path)
    back = spark.read.schema(df.schema).parquet(path).select(*df.columns)
    back._stored_at = path
    return back


def bucketed(df: DataFrame, label: str, key: str, buckets: int | None = None) -> DataFrame:
    """Like `written`, laid out by hash of `key` in buckets (None: as many as a shuffle has partitions) and sorted in
    each: joins and groupings on the key read it without a shuffle."""
    spark, path = df.sparkSession, new_path(df.sparkSession, label)
    name = f"{label.replace('-', '_')}_{uuid.uuid4().hex}"
    buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    with shuffles_dropped(spark):
        df.repartition(buckets, key).write.option("path", path).option("compression", "zstd").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    back = spark.table(name)
    back._stored_at, back._stored_as = path, name
    return back


def drop_written(*tables: DataFrame) -> None:
    """Delete tables that `written` or `bucketed` made and nothing reads any more."""
    for t in tables:
        if getattr(t, "_stored_as", None):
            t.sparkSession.sql(f"DROP TABLE IF EXISTS {t._stored_as}")
        if getattr(t, "_stored_at", None):
            remove(t.sparkSession, t._stored_at)


#: Ids that may be broadcast: 16 MB of longs, a few times that as a hash table.
BROADCAST_ROWS = 2_000_000


def fits_broadcast(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether df has at most `rows` rows: asked before any broadcast of something that grows with the data. Counts per
    partition, so no row moves; cheapest on written tables, whose footers hold the count."""
    return df.count() <= rows


@dataclass
class Rounds:
    """What an iterative method took: its own steps, and the Spark jobs that the scheduler counted meanwhile."""

    levels: int = 0
    jobs: int = 0
    sweeps: int = 0
    waves: int = 0
    _inside: int = 0

    @contextmanager
    def counted(self, spark: SparkSession) -> Iterator[None]:
        """Add the jobs that run inside."""
        scheduler = spark.sparkContext._jsc.sc().dagScheduler()
        before, self._inside = scheduler.numTotalJobs(), self._inside + 1
        try:
            yield
        finally:
            self._inside -= 1
            if not self._inside:  # a method inside another one is counted once
                self.jobs += scheduler.numTotalJobs() - before

    def row(self, method: str) -> tuple:
        return (method, self.levels, self.jobs, self.sweeps, self.waves)
