"""Edge lists in files, and graphs and answers under SQL names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.graph import Graph

FORMATS = ("csv", "json", "orc", "text", "parquet")


def read_edges(spark: SparkSession, path: str, fmt: str, separator: str = " ") -> tuple[DataFrame, DataFrame]:
    """(edges (x, y), lines that are no edge (line)) of a file or folder of edges in one of FORMATS.

    A line of ``text`` or ``csv`` holds two whole numbers; an object of ``json`` has x and y.  Lines that
    do not parse are set aside, not dropped."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format: {fmt}")
    if fmt in ("orc", "parquet"):
        rows = spark.read.format(fmt).load(path).select(F.col("x").cast("bigint").alias("x"), F.col("y").cast("bigint").alias("y"))
        return rows, spark.createDataFrame([], "line string")
    lines = spark.read.text(path).select(F.col("value").alias("line"))
    if fmt == "json":
        parsed = lines.withColumn("e", F.from_json("line", "x bigint, y bigint"))
        good = F.col("e.x").isNotNull() & F.col("e.y").isNotNull()
        return parsed.filter(good).select("e.x", "e.y"), parsed.filter(~good).select("line")
    by = "," if fmt == "csv" else separator
    fields = lines.withColumn("f", F.split(F.trim("line"), f"\\s*{by}\\s*" if fmt == "csv" else r"\s+"))
    number = lambda i: F.get("f", F.lit(i)).try_cast("bigint")
    parsed = fields.select("line", F.size("f").alias("n"), number(0).alias("x"), number(1).alias("y"))
    good = (F.col("n") == 2) & F.col("x").isNotNull() & F.col("y").isNotNull()
    return parsed.filter(good).select("x", "y"), parsed.filter(~F.coalesce(good, F.lit(False))).select("line")


def write_edges(edges: DataFrame, path: str, fmt: str, separator: str = " ") -> None:
    """The counterpart of ``read_edges`` for edges (x, y)."""
    if fmt in ("orc", "parquet"):
        edges.write.format(fmt).save(path)
    elif fmt == "json":
        edges.select(F.to_json(F.struct("x", "y")).alias("value")).write.text(path)
    else:
        edges.select(F.concat_ws("," if fmt == "csv" else separator, F.col("x").cast("string"), F.col("y").cast("string")).alias("value")).write.text(path)


def register(name: str, graph: Graph, **answers: DataFrame) -> list[str]:
    """SQL names ``v_<name>_vertices``, ``v_<name>_edges`` and ``v_<name>_<answer>`` for a graph and its answers."""
    views = {"vertices": graph.vertices, "edges": graph.edges, **answers}
    for part, df in views.items():
        df.createOrReplaceTempView(f"v_{name}_{part}")
    return [f"v_{name}_{part}" for part in views]
