"""Connected components by hooking and contraction.

Every round hooks each vertex onto its least neighbour, flattens the resulting forest by
pointer doubling, and rewrites the edges between roots.  Vertices at least halve in a
round, so rounds are logarithmic whatever the diameter; what is left below
``local.CORPUS_ROWS`` edges is ended in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import discard, materialize, measured
from . import local


def flatten(parent: DataFrame, max_rounds: int = 64) -> DataFrame:
    """(vid, root) from (vid, parent) where roots point at themselves and parents are smaller."""
    now = materialize(parent.select("vid", F.col("parent").alias("root")), "hooks")
    for _ in range(max_rounds):
        up = now.select(F.col("vid").alias("root"), F.col("root").alias("above"))
        moved = (F.col("above") != F.col("root")).cast("long")
        step = now.join(up, "root").select("vid", "root", "above")
        then, seen = measured(step.select("vid", F.col("above").alias("root"), moved.alias("moved")), "hooks", moved=F.col("moved"))
        discard(now)
        now = then.select("vid", "root")
        now._scratch_path = then._scratch_path
        if seen["moved"] == 0:
            return now
    raise RuntimeError("the forest did not flatten")


def contract_components(edges: DataFrame, max_rounds: int = 64, rows: int | None = None, end=None) -> DataFrame:
    """(vid, comp) with comp the least vertex of the component, for all end points of edges (a, b).

    ``end`` makes (vid, root) of the last edges once ``rows`` or fewer are left; by default one task does, below ``local.CORPUS_ROWS``."""
    edge = materialize(edges.filter("a is not null and b is not null").select(F.least("a", "b").cast("bigint").alias("a"), F.greatest("a", "b").cast("bigint").alias("b")).distinct(), "edges")
    ends = edge.select(F.explode(F.array("a", "b")).alias("vid")).distinct()
    live, label = edge.filter("a <> b"), None
    left = live.count()
    for _ in range(max_rounds):
        if left == 0:
            break
        if left <= (min(local.ROWS, local.CORPUS_ROWS) if rows is None else rows):
            done = end(live) if end else local.local_forest(live.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb"))).filter("vid is not null").select("vid", "root")
            root, left, fewer = materialize(done, "hooks"), 0, None
        else:
            arcs = live.select(F.explode(F.array(F.struct(F.col("a").alias("vid"), F.col("b").alias("other")), F.struct(F.col("b").alias("vid"), F.col("a").alias("other")))).alias("arc"))
            hooks = arcs.select("arc.*").groupBy("vid").agg(F.min("other").alias("other")).select("vid", F.least("vid", "other").alias("parent"))
            root = flatten(hooks)
            x = root.select(F.col("vid").alias("a"), F.col("root").alias("ra"))
            y = root.select(F.col("vid").alias("b"), F.col("root").alias("rb"))
            fewer = materialize(live.join(x, "a").join(y, "b").filter("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(), "contracted")
            left = fewer.count()
        discard(live)
        live = fewer
        if label is None:
            label = root
        else:
            step = root.select(F.col("vid").alias("root"), F.col("root").alias("next"))
            lower = materialize(label.join(step, "root", "left").select("vid", F.coalesce("next", "root").alias("root")), "labels")
            discard(label, root)
            label = lower
    if label is None:
        return ends.select("vid", F.col("vid").alias("comp"))
    return ends.join(label, "vid", "left").select("vid", F.coalesce("root", "vid").alias("comp"))
