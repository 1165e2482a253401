"""Scratch tables in the cluster's shared folder.

Iterative methods cut their lineage here: a table is written once and read back, so a
lost executor costs a re-read and never a recomputation of earlier rounds.  The shuffle
files of such a write go when it ends, and a table goes when its maker discards it.
"""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

SHUFFLE_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def scratch_dir(spark: SparkSession) -> str:
    """The session's spark.checkpoint.dir; where none is set, a temporary folder in local mode and an error on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="lwgraph-scratch-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def new_scratch_path(spark: SparkSession, name: str) -> str:
    return f"{scratch_dir(spark)}/lwgraph/{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex[:12]}"


@contextmanager
def session_setting(spark: SparkSession, key: str, value):
    """A setting of the session for a while; its own value returns afterwards."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write once to the shared folder and read back."""
    spark = df.sparkSession
    path = new_scratch_path(spark, name)
    with session_setting(spark, SHUFFLE_CLEANUP, "true"):
        df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def barrier(df: DataFrame, mode: str = "parquet", name: str = "barrier") -> DataFrame:
    """The same rows with their lineage cut: ``parquet`` writes a table and reads it back, ``reliable`` uses Spark's checkpoint.

    Both write to the shared folder; nothing is kept on an executor alone."""
    if mode == "parquet":
        return materialize(df, name)
    if mode != "reliable":
        raise ValueError(f"unknown barrier: {mode}")
    scratch_dir(df.sparkSession)
    if df.sparkSession.sparkContext.getCheckpointDir() is None:
        df.sparkSession.sparkContext.setCheckpointDir(scratch_dir(df.sparkSession))
    return df.checkpoint(eager=True)


def discard(*tables: DataFrame | None) -> None:
    """Remove tables that ``materialize`` wrote and nothing reads any more."""
    for table in tables:
        path = getattr(table, "_scratch_path", None)
        if path:
            remove_path(table.sparkSession, path)


def remove_path(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class Watch:
    """Figures of a plan's rows, taken while they pass: their number as ``rows``, and sums."""

    def __init__(self, **sums: Column):
        self.names = ["rows", *sums]
        self.totals = [F.count(F.lit(1)).alias("rows"), *[F.sum(c).alias(k) for k, c in sums.items()]]
        self.observation, self.bus = Observation(), None

    def over(self, df: DataFrame) -> DataFrame:
        self.bus = df.sparkSession.sparkContext._jsc.sc().listenerBus()
        return df.observe(self.observation, *self.totals)

    def figures(self) -> dict | None:
        """Ask when the query has ended; None where the plan was cut off above the place because nothing could come from it."""
        self.bus.waitUntilEmpty(60_000)
        row = self.observation._jo.getRowOrEmpty()
        if not row.isDefined() or row.get().length() != len(self.names):
            return None
        return {k: row.get().get(i) or 0 for i, k in enumerate(self.names)}

    @property
    def rows(self) -> int:
        return (self.figures() or {"rows": 0})["rows"]


def watched(df: DataFrame) -> tuple[DataFrame, Watch]:
    """The same rows, counted where they stand in the plan."""
    watch = Watch()
    return watch.over(df), watch


def measured(df: DataFrame, name: str, **sums: Column) -> tuple[DataFrame, dict]:
    """``materialize``, with the number of rows and sums over them taken while they are written.

    A stage that runs again after a lost executor may count rows twice: use the figures as measures,
    and for decisions only whether they are zero."""
    watch = Watch(**sums)
    out = materialize(watch.over(df), name)
    return out, watch.figures() or {k: v or 0 for k, v in out.agg(*watch.totals).head().asDict().items()}
