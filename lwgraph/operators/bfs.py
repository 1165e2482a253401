"""Level-synchronous search that stores only newly reached vertices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.adjacency import adjacency
from ..plans.graph import CostMeter, Graph
from ..plans.scratch import measured, watched
from . import local


def levels(graph: Graph, sources: DataFrame, *, max_hops: int | None = None, meter: CostMeter | None = None, order: str = "vid") -> DataFrame:
    """(vid, source, hop, parent): nearest source by hops, then by the least path.

    The parent of a vertex is its least neighbour one level nearer, so following parents
    gives the lexicographically least shortest path to a source; ``order="hash"`` ranks vertices
    by a hash of their id instead.  Messages of a level are transient; what is kept is one row a
    vertex reached.  Neighbours of a level lie in it, in the one before or in the next one, so
    that only two levels are read to find what is new.  Without a bound on hops one task ends the search
    once the arcs of what is not reached are those of ``local.ROWS`` edges or fewer."""
    start = sources.select(F.col(sources.columns[0]).alias("vid")).distinct().select("vid", F.col("vid").alias("source"), F.lit(0).alias("hop"), F.lit(None).cast("bigint").alias("parent"))
    front, seen = measured(start, "levels")
    if meter:
        meter.add("level", writes=seen["rows"])
    if max_hops is None:
        last = _last_levels(graph, graph.arcs(), [front], 0, order, meter)
        if last is not None:
            return front.unionByName(last)
    left = graph.vertices.count() - seen["rows"]
    with adjacency(graph) as arcs:
        layers, hop = [front], 0
        rank = F.col("src") if order == "vid" else F.xxhash64("src")
        while seen["rows"] and (max_hops is None or hop < max_hops):
            sent, looked = watched(front.select(F.col("vid").alias("src"), "source").join(arcs.select("src", "dst"), "src"))
            # one neighbour has one source: two hash aggregates, no struct to sort by
            reached = sent.groupBy("dst").agg(F.min_by("src", rank).alias("parent"), F.min_by("source", rank).alias("source")) \
                .select(F.col("dst").alias("vid"), "source", F.lit(hop + 1).alias("hop"), "parent")
            known = layers[-1].select("vid") if len(layers) == 1 else layers[-1].select("vid").unionByName(layers[-2].select("vid"))
            front, seen = measured(reached.join(known, "vid", "left_anti"), "levels")
            if meter:
                meter.add("level", ops=looked.rows, writes=seen["rows"], rounds=1, scratch_peak=seen["rows"])
            if seen["rows"]:
                layers.append(front)
                hop += 1
                left -= seen["rows"]
                if max_hops is None and left <= local.ROWS:
                    last = _last_levels(graph, arcs, layers, hop, order, meter)
                    if last is not None:
                        layers.append(last)
                        break
    out = layers[0]
    for x in layers[1:]:
        out = out.unionByName(x)
    return out


def _last_levels(graph: Graph, arcs: DataFrame, layers: list[DataFrame], hop: int, order: str, meter: CostMeter | None) -> DataFrame | None:
    """The levels after ``hop`` by one task, from the arcs of all vertices not yet reached; None where those are too many."""
    if len(layers) == 1 and graph.edges.count() > local.ROWS:
        return None
    met = layers[0].select("vid")
    for x in layers[1:]:
        met = met.unionByName(x.select("vid"))
    near = F.col("dst") if order == "vid" else F.xxhash64("dst")
    open_ = arcs.join(met.withColumnRenamed("vid", "src"), "src", "left_anti").select(F.col("src").alias("vid"), F.col("dst").alias("near"), near.alias("rank"))
    looked = None
    if len(layers) > 1:
        open_, looked = measured(open_, "levels-open")
        if open_.count() > 2 * local.ROWS:
            return None
    else:
        open_, looked = watched(open_)
    rows, seen = measured(local.local_levels(open_, layers[-1]).withColumn("hop", (F.col("hop") + hop).cast("int")), "levels")
    if meter:
        deepest = rows.agg(F.max("hop")).head()[0] or hop
        meter.add("level", ops=looked["rows"] if isinstance(looked, dict) else looked.rows, writes=seen["rows"], rounds=deepest - hop + 1, scratch_peak=seen["rows"])
    return rows
