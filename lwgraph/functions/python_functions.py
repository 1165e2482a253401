"""Python functions where expressions do not reach: Arrow scalars, grouped aggregates, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two float arrays of equal length; null if either has no length."""
    out = []
    for x, y in zip(a, b, strict=True):
        x, y = np.asarray(x, float), np.asarray(y, float)
        n = np.linalg.norm(x) * np.linalg.norm(y)
        out.append(float(x @ y / n) if n else None)
    return pd.Series(out, dtype="float64")


def cosine_expression(a: str, b: str):
    """The same as an expression; preferred, it stays in generated code."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


@F.pandas_udf(T.LongType())
def component_count(a: pd.Series, b: pd.Series) -> int:
    """Number of components of a group's edges (small groups)."""
    root: dict = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for x, y in zip(a, b, strict=True):
        p, q = find(x), find(y)
        root[max(p, q)] = min(p, q)
    return len({find(x) for x in list(root)})


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in ("vid", "node", "parent")]))
class ExpandVertex:
    """Tree nodes of a vertex of high degree."""

    def eval(self, vid: int, degree: int, cap: int):
        leaves = -(-degree // cap) if degree > cap else 0
        for i in range(1, 2 * leaves):
            yield vid, i, i // 2 if i > 1 else None


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in ("qid", "vid", "hop")]))
class BoundedSearch:
    """Vertices within some hops of a start, for one question's edges: a table argument partitioned by the question.

    Rows are (qid, start, a, b); an edge without an end only names a vertex.  A partition holds one neighbourhood."""

    def __init__(self):
        self.near: dict[int, set[int]] = {}
        self.start = self.qid = None
        self.hops = 3

    def eval(self, row):
        self.qid, self.start = row["qid"], row["start"]
        self.near.setdefault(self.start, set())
        if row["a"] is not None and row["b"] is not None:
            self.near.setdefault(row["a"], set()).add(row["b"])
            self.near.setdefault(row["b"], set()).add(row["a"])

    def terminate(self):
        if self.start is None:
            return
        seen, front = {self.start: 0}, [self.start]
        for hop in range(1, self.hops + 1):
            front = sorted({w for v in front for w in self.near.get(v, ()) if w not in seen})
            seen.update(dict.fromkeys(front, hop))
        for v, hop in seen.items():
            yield self.qid, v, hop


def register(spark: SparkSession) -> None:
    spark.udtf.register("lw_bounded_search", BoundedSearch)
    spark.udf.register("lw_cosine", cosine)
    spark.udf.register("lw_component_count", component_count)
    spark.udtf.register("lw_expand_vertex", ExpandVertex)
