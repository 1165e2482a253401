"""Degree expansion: a vertex of high degree becomes a small tree whose leaves take its edges.

Keeps connectivity, whether an original edge is a bridge, and two-edge classes that ignore the
trees' own edges.  It does not keep blocks: an expanded graph refuses them, and ``plans.solve``
sends such questions to the dense method, whatever the degree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.graph import CostMeter, Graph
from ..plans.scratch import materialize, measured
from .trees import global_index

LARGEST = 1 << 62


def _positions(graph: Graph, positions: str, meter: CostMeter | None) -> DataFrame:
    """(src, dst, mult, pos): the place of every edge in both its lists.

    ``stored`` keeps one row an arc; ``search`` finds the place anew in the sorted lists and keeps nothing."""
    if positions not in ("stored", "search"):
        raise ValueError(f"unknown way to find positions: {positions}")
    if positions == "search":
        return graph.adjacency()
    kept, seen = measured(graph.adjacency(), "positions")
    if meter:
        meter.add("edge positions", ops=seen["rows"], writes=seen["rows"], rounds=1)
    return kept


def expand(graph: Graph, cap: int, *, positions: str = "search", explicit: bool = False, meter: CostMeter | None = None) -> tuple[Graph, DataFrame]:
    """(bounded graph, vertex map (node, vid)).

    A vertex with more than ``cap`` neighbours gets ceil(degree / cap) leaves, numbered as
    in a heap; edge i of its list hangs under leaf i div cap.  Node i's parent is i div 2,
    computed, not stored.  The graph is a plan; ``explicit`` stores it.  Node i of the vertex that
    stands at place v is v * shift + i, with a shift above the largest heap; vertices stand at
    their own ids, or are numbered where ids are negative or too large for that."""
    adj = _positions(graph, positions, meter)
    deg = adj.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    shape = deg.withColumn("leaves", F.when(F.col("deg") > cap, F.ceil(F.col("deg") / cap)).otherwise(0).cast("bigint"))
    most = shape.agg(F.max("leaves")).head()[0] or 0
    shift = 1 << (2 * most).bit_length()
    low, high = graph.vertices.agg(F.min("vid"), F.max("vid")).head()
    if low is None or (low >= 0 and (high + 1) * shift < LARGEST):
        place = graph.vertices.select("vid", F.col("vid").alias("at"))
    else:
        place = materialize(global_index(graph.vertices, ["vid"], "at").select("vid", "at"), "places")
    shape = shape.join(place.withColumnRenamed("vid", "src"), "src")
    placed = adj.join(shape, "src").select("src", "dst", "mult", F.when(F.col("leaves") > 0, F.col("at") * shift + F.col("leaves") + F.expr(f"pos div {cap}")).otherwise(F.col("at") * shift).alias("node"))
    there = placed.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("node").alias("other"))
    real = placed.join(there, ["src", "dst"]).filter("src < dst").select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b"), "mult")
    heaps = shape.filter("leaves > 0").select("at", F.explode(F.expr("sequence(2L, 2 * leaves - 1)")).alias("i"))
    inner = heaps.select((F.col("at") * shift + F.expr("i div 2")).alias("a"), (F.col("at") * shift + F.col("i")).alias("b"), F.lit(1).alias("mult"))
    nodes = place.join(shape.select(F.col("src").alias("vid"), "leaves"), "vid", "left").select("vid", "at", F.explode(F.when(F.coalesce("leaves", F.lit(0)) > 0, F.expr("sequence(1L, 2 * leaves - 1)")).otherwise(F.array(F.lit(0).cast("bigint")))).alias("i"))
    names = nodes.select((F.col("at") * shift + F.col("i")).alias("node"), "vid")
    out = Graph(names.select(F.col("node").alias("vid")), real.unionByName(inner), expanded=True)
    if explicit:
        out = out.fixed("expanded")
        if meter:
            meter.add("expanded graph", writes=out.vertices.count() + out.edges.count(), rounds=1)
    return out, names


def project_components(comp: DataFrame, names: DataFrame) -> DataFrame:
    """(vid, comp) of the original graph from classes of the expanded one, named by their least vertex."""
    joined = comp.withColumnRenamed("vid", "node").join(names, "node").select("vid", "comp").distinct()
    least = joined.groupBy("comp").agg(F.min("vid").alias("name"))
    return joined.join(least, "comp").select("vid", F.col("name").alias("comp"))


def project_edges(found: DataFrame, names: DataFrame) -> DataFrame:
    """(a, b) of original edges from edges of the expanded graph; those inside one vertex's tree drop."""
    x, y = names.toDF("a", "va"), names.toDF("b", "vb")
    ends = found.select("a", "b").join(x, "a").join(y, "b").filter("va <> vb")
    return ends.select(F.least("va", "vb").alias("a"), F.greatest("va", "vb").alias("b"))


def two_edge_classes(graph: Graph, cap: int, **options) -> DataFrame:
    """(vid, comp) of the original graph through the expanded one: only bridges between trees cut, a tree's own edges never."""
    from .blocks import block_labelling, bridges
    from .connect import components_star

    wide, names = expand(graph, cap, **options)
    wide, names = wide.fixed("expanded"), materialize(names, "names")
    cut = project_edges(bridges(block_labelling(wide, beta=0.5)), names)
    rest = graph.edges.join(cut, ["a", "b"], "left_anti")
    return components_star(Graph(graph.vertices, rest))
