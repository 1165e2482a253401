"""Generated graphs as a data source: partitions are ranges of vertex ids, edges are made where they are read."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

NAME = "lw_edges"


class IdRange(InputPartition):
    def __init__(self, first: int, stop: int):
        self.first, self.stop = first, stop


class EdgeReader(DataSourceReader):
    def __init__(self, kind: str, n: int, parts: int):
        self.kind, self.n, self.parts = kind, n, parts

    def partitions(self) -> list[IdRange]:
        total = self.n * self.n if self.kind == "grid" else self.n
        step = max(1, -(-total // self.parts))
        return [IdRange(i, min(total, i + step)) for i in range(0, max(1, total), step)]

    def read(self, partition: IdRange) -> Iterator[tuple[int, int]]:
        n = self.n
        for v in range(partition.first, partition.stop):
            if self.kind == "grid":
                if v % n < n - 1:
                    yield v, v + 1
                if v + n < n * n:
                    yield v, v + n
            elif self.kind == "path":
                if v + 1 < n:
                    yield v, v + 1
            elif self.kind == "star":
                if v:
                    yield 0, v
            else:
                yield from ((v, w) for w in range(v + 1, n))


class EdgeSource(DataSource):
    """Options: ``kind`` (grid, path, star, clique), ``n`` (side of the grid, else vertices), ``parts``."""

    @classmethod
    def name(cls) -> str:
        return NAME

    def schema(self) -> str:
        return "x bigint, y bigint"

    def reader(self, schema) -> EdgeReader:
        kind = self.options.get("kind", "path")
        if kind not in ("grid", "path", "star", "clique"):
            raise ValueError(f"unknown kind of graph: {kind}")
        return EdgeReader(kind, int(self.options.get("n", 0)), int(self.options.get("parts", 8)))


def grid_over(keys: DataFrame, width: int) -> DataFrame:
    """(x, y): the rows of a table of one column laid out in its order, ``width`` to a line, each linked to the next of its line and to the one below."""
    from ..operators.trees import global_index
    from ..plans.scratch import materialize

    (key,) = keys.columns
    at = materialize(global_index(keys, [key], "i"), "grid")
    beside = F.when(F.col("i") % width < width - 1, F.col("i") + 1)
    ends = at.select(F.col(key).alias("x"), F.explode(F.array_compact(F.array(beside, F.col("i") + width))).alias("i"))
    return ends.join(at.select("i", F.col(key).alias("y")), "i").select("x", "y")


def generated(spark: SparkSession, kind: str, n: int, parts: int = 8) -> DataFrame:
    """(x, y) of a generated graph."""
    spark.dataSource.register(EdgeSource)
    return spark.read.format(NAME).options(kind=kind, n=str(n), parts=str(parts)).load()
