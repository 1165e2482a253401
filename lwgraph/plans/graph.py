"""The graph relation, its cost meter, predicted costs and the choice of a method."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import materialize


class ScopeError(ValueError):
    """The question has no answer on this graph."""


@dataclass
class Graph:
    """An undirected multigraph: vertices(vid), edges(a, b, mult) with a < b, no loops."""

    vertices: DataFrame
    edges: DataFrame
    expanded: bool = False  # high degrees were replaced by trees: blocks are not those of the original
    stored: bool = False  # both are tables already
    held: dict = field(default_factory=dict, compare=False, repr=False)  # by order: places of the vertices and arcs in arrays, for tasks that search

    @classmethod
    def of(cls, pairs: DataFrame, vertices: DataFrame | None = None) -> Graph:
        """From any two-column pairs: null ends and loops drop, duplicates become ``mult``."""
        x, y = pairs.columns[:2]
        ends = pairs.select(F.col(x).cast("bigint").alias("x"), F.col(y).cast("bigint").alias("y")).filter("x is not null and y is not null")
        edges = ends.filter("x <> y").groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count(F.lit(1)).cast("int").alias("mult"))
        named = ends.select(F.explode(F.array("x", "y")).alias("vid"))
        if vertices is not None:
            named = named.unionByName(vertices.select(F.col(vertices.columns[0]).cast("bigint").alias("vid")).filter("vid is not null"))
        return cls(named.distinct(), edges)

    def arcs(self) -> DataFrame:
        """(src, dst, mult): both directions of every edge in one scan."""
        both = F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))))
        return self.edges.select(both.alias("arc"), "mult").select("arc.src", "arc.dst", "mult")

    def adjacency(self) -> DataFrame:
        """Arcs with the position of each neighbour in its vertex's list, from 0."""
        from pyspark.sql import Window

        return self.arcs().withColumn("pos", F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1)

    def fixed(self, name: str = "graph") -> Graph:
        """The same graph, written once."""
        if self.stored:
            return self
        return Graph(materialize(self.vertices, f"{name}-vertices"), materialize(self.edges, f"{name}-edges"), self.expanded, True)

    def refuse_expanded(self, what: str) -> None:
        if self.expanded:
            raise ScopeError(f"{what} of an expanded graph are not those of the original: use the dense method on the original graph")

    def max_degree(self) -> int:
        return self.arcs().groupBy("src").count().agg(F.max("count")).head()[0] or 0


@dataclass
class CostMeter:
    """Counts what a method stores (writes), what it looks at (ops) and its rounds; work at any write cost follows."""

    method: str = ""
    rows: list[tuple] = field(default_factory=list)

    def add(self, stage: str, ops: int = 0, writes: int = 0, rounds: int = 0, scratch_peak: int = 0) -> None:
        self.rows.append((self.method, stage, int(ops), int(writes), int(rounds), int(scratch_peak)))

    def total(self) -> tuple[int, int, int]:
        return sum(r[2] for r in self.rows), sum(r[3] for r in self.rows), sum(r[4] for r in self.rows)

    def peak(self) -> int:
        """The most rows that one round held beside what is kept."""
        return max((r[5] for r in self.rows), default=0)

    def report(self, spark, omegas=(1,)) -> DataFrame:
        """(method, stage, ops, writes, rounds, scratch_peak, omega, work)."""
        made = spark.createDataFrame(self.rows, "method string, stage string, ops long, writes long, rounds long, scratch_peak long")
        return made.withColumn("omega", F.explode(F.array(*[F.lit(int(w)) for w in omegas]))).withColumn("work", F.col("ops") + F.col("omega") * F.col("writes"))


def choose_method(n: int, m: int, omega: float, max_degree: int | None = None, bound: int = 16) -> dict:
    """Dense family when m >= sqrt(omega) n, else the sparse one with k = sqrt(omega)."""
    root = math.sqrt(omega)
    dense = m >= root * n
    wide = max_degree is not None and max_degree > bound
    return {"family": "dense" if dense else "sparse", "k": max(1, round(root)), "beta": 1 / max(1.0, omega) if dense else 1 / max(1.0, root),
            "degree": "as is" if not wide or dense else "expand; blocks and articulation points by the dense method"}


def predicted(n: int, m: int, omega: float, k: int | None = None) -> list[tuple[str, float, float, float]]:
    """(method, operations, writes, work) of the published bounds, constants left out."""
    k = k or max(1, round(math.sqrt(omega)))
    table = [
        ("connectivity, breadth-first", m, n), ("connectivity, recursive contraction", m, m), ("connectivity, low-write", m + n, n + m / omega),
        ("biconnectivity, edge array", m, m), ("biconnectivity, block labelling", m + n, n + m / omega),
        ("decomposition", k * n, n / k), ("connectivity oracle", k * n + k * m / k, n / k), ("biconnectivity oracle", k * n, n / k),
    ]
    return [(name, float(ops), float(writes), float(ops + omega * writes)) for name, ops, writes in table]


def calibrate_omega(spark, rows: int = 200_000) -> float:
    """Seconds to write a row over seconds to scan one, on this session."""
    import time

    from .scratch import new_scratch_path

    path = new_scratch_path(spark, "calibrate")
    made = spark.range(rows).select("id", F.xxhash64("id").alias("h"))
    t0 = time.time()
    made.write.parquet(path)
    t1 = time.time()
    spark.read.parquet(path).agg(F.max("h")).collect()
    return max(1.0, (t1 - t0) / max(1e-3, time.time() - t1))
