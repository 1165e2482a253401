"""Shared helpers: table reads, scratch tables in the shared folder, packed rows."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import discard, materialize, new_scratch_path, remove_path, scratch_dir, session_setting  # noqa: F401


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def ascii_lower(col):
    """Lower-case A-Z only; every other character is left as it is."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@contextmanager
def arrow_batches(spark: SparkSession, rows: int, size: int = 4 << 20):
    """Arrow batches of at most so many rows and about so many bytes, for steps whose rows are wide."""
    with session_setting(spark, "spark.sql.execution.arrow.maxRecordsPerBatch", rows), session_setting(spark, "spark.sql.execution.arrow.maxBytesPerBatch", size):
        yield
