"""Adjacency lists bucketed by their vertex: frontier joins move the frontier only."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

from .graph import Graph
from .scratch import new_scratch_path, remove_path


def save_adjacency(graph: Graph, name: str, buckets: int, path: str | None = None) -> DataFrame:
    """(src, dst, mult) as a table with ``buckets`` buckets by src, each sorted by (src, dst), one file a bucket."""
    writer = graph.arcs().repartition(buckets, "src").write.bucketBy(buckets, "src").sortBy("src", "dst").format("parquet").mode("overwrite")
    (writer.option("path", path) if path else writer).saveAsTable(name)
    return graph.vertices.sparkSession.table(name)


def bucket_count(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


@contextmanager
def adjacency(graph: Graph):
    """The lists of a graph for the rounds of one method; the table goes afterwards."""
    spark = graph.vertices.sparkSession
    name, path = f"lw_adjacency_{uuid.uuid4().hex[:12]}", new_scratch_path(spark, "adjacency")
    try:
        yield save_adjacency(graph, name, bucket_count(spark), path)
    finally:
        spark.sql(f"drop table if exists {name}")
        remove_path(spark, path)
