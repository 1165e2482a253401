"""Shifted-ball (low-diameter) partition: delayed growth from exponentially shifted starts."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.adjacency import adjacency
from ..plans.graph import CostMeter, Graph
from ..plans.scratch import discard, materialize, measured, watched


def shifts(vertices: DataFrame, beta: float, seed: int = 0, *, start_rule: str = "shifted", start_cap: int | None = None) -> DataFrame:
    """(vid, start INT, frac): exponential delays with mean 1/beta, from a hash of (seed, vid).

    ``shifted`` lets the largest delay start first, which is what bounds the cut edges;
    ``literal`` starts a vertex at its own delay and is kept as an ablation."""
    u = (F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("vid").cast("string"))), 1, 12), 16, 10).cast("double") + 1) / F.lit(float(16**12 + 1))
    delays = vertices.select("vid", (-F.log(u) / beta).alias("delay"))
    if start_rule == "literal":
        begin = F.col("delay")
    else:
        top = delays.agg(F.max("delay")).head()[0] or 0.0
        begin = F.lit(top) - F.col("delay")
    begin = F.least(begin, F.lit(float(start_cap))) if start_cap is not None else begin
    return delays.select("vid", F.floor(begin).cast("int").alias("start"), (begin - F.floor(begin)).alias("frac"))


SEEN_TABLES = 8  # levels that are read one by one before they are merged


def ball_partition(graph: Graph, beta: float, seed: int = 0, *, start_rule: str = "shifted", tie_rule: str = "min_id", start_cap: int | None = None,
                   materialize_messages: bool = False, parents: bool = True, meter: CostMeter | None = None) -> DataFrame:
    """(vid, source, hop, parent) for every vertex; ``parent`` spans each ball by shortest paths, null without ``parents``.

    Each round grows the frontier by a hop and admits the vertices whose start has come.
    Rounds in which nothing can happen are skipped.  A neighbour of what was reached in one
    round was reached in that round, the one before, or will be in the next: messages are held
    against two rounds, only vertices that start against all.  ``materialize_messages`` stores
    every message as the classical search does, for comparison."""
    starts, seen = measured(shifts(graph.vertices, beta, seed, start_rule=start_rule, start_cap=start_cap), "starts")
    if meter:
        meter.add("starts", ops=seen["rows"], writes=seen["rows"])
    left = [r[0] for r in starts.groupBy("start").count().select("start").orderBy("start").toLocalIterator()]  # one number a round, O(log n / beta) of them
    total, reached, layers, time = seen["rows"], 0, [], left[0] if left else 0
    known: list[DataFrame] = []  # vertices of all layers, merged now and then
    recent: list[DataFrame | None] = [None, None]  # this round and the one before; None where it was empty
    with adjacency(graph) as arcs:
        while True:
            fresh = starts.filter(F.col("start") == time).select("vid", F.col("vid").alias("source"), F.lit(0).alias("hop"), "frac")
            for table in known:
                fresh = fresh.join(table, "vid", "left_anti")
            front, looked = recent[0], None
            if front is not None:
                sent, looked = watched(front.select(F.col("vid").alias("src"), "source", "hop", "frac").join(arcs.select("src", "dst"), "src").select(F.col("dst").alias("vid"), "source", (F.col("hop") + 1).alias("hop"), "frac"))
                if materialize_messages:
                    sent, told = measured(sent, "messages")
                    if meter:
                        meter.add("messages", writes=told["rows"])
                fresh = fresh.unionByName(sent)
            # the winner's source, hop and fraction: hash aggregates, a source has one hop count a round
            best = F.col("frac") if tie_rule == "fraction" else F.col("source")
            won = fresh.groupBy("vid").agg(F.min_by("source", best).alias("source"), F.min_by("hop", best).alias("hop"), F.min_by("frac", best).alias("frac"))
            for table in recent:
                if table is not None:
                    won = won.join(table.select("vid"), "vid", "left_anti")
            front, seen = measured(won, "ball-level")
            n = seen["rows"]
            reached += n
            if meter:
                meter.add("growth", ops=looked.rows if looked else 0, writes=n, rounds=1, scratch_peak=n)
            recent = [front if n else None, recent[0]]
            if n:
                layers.append(front)
                known.append(front.select("vid"))
                if len(known) == SEEN_TABLES:
                    merged = known[0]
                    for table in known[1:]:
                        merged = merged.unionByName(table)
                    merged, told = measured(merged, "ball-known")
                    known = [merged]
                    if meter:
                        meter.add("growth", writes=told["rows"])
                time += 1
                # a count of a repeated stage may be too high: only an exact one ends the rounds early
                if reached >= total and sum(x.count() for x in layers) >= total:
                    break
            else:  # no messages are under way: go on where the next vertex starts
                later = [s for s in left if s > time]
                if not later:
                    break
                recent, time = [None, None], later[0]
    if not layers:
        return graph.vertices.select("vid", F.col("vid").alias("source"), F.lit(0).alias("hop"), F.lit(None).cast("bigint").alias("parent"))
    out = layers[0]
    for x in layers[1:]:
        out = out.unionByName(x)
    out = out.select("vid", "source", "hop", F.lit(None).cast("bigint").alias("parent"))
    if parents:
        out = with_parents(graph, out, meter)
    out, told = measured(out, "balls")
    discard(starts, *layers)
    if meter:
        meter.add("balls", writes=told["rows"])
    return out


def with_parents(graph: Graph, ball: DataFrame, meter: CostMeter | None = None) -> DataFrame:
    """``ball`` with the least neighbour of the same ball one hop nearer its source: one pass over the edges, not one a round."""
    near = ball.select(F.col("vid").alias("src"), "source", (F.col("hop") + 1).alias("hop"))
    sent, looked = watched(near.join(graph.arcs().select("src", "dst"), "src").select(F.col("dst").alias("vid"), "source", "hop", "src"))
    found = sent.join(ball.select("vid", "source", "hop"), ["vid", "source", "hop"], "left_semi").groupBy("vid").agg(F.min("src").alias("parent"))
    out = materialize(ball.drop("parent").join(found, "vid", "left").select("vid", "source", "hop", "parent"), "ball-parents")
    if meter:
        meter.add("ball trees", ops=looked.rows)
    return out


def ball_trees(ball: DataFrame) -> DataFrame:
    """Tree edges (a, b) inside the balls."""
    return ball.filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"))


def crossing(graph: Graph, ball: DataFrame) -> DataFrame:
    """Edges between balls: (ra, rb) original ends and (a, b) their ball sources, only survivors."""
    x, y = ball.select(F.col("vid").alias("a"), F.col("source").alias("sa")), ball.select(F.col("vid").alias("b"), F.col("source").alias("sb"))
    return graph.edges.select("a", "b").join(x, "a").join(y, "b").filter("sa <> sb").select(F.least("sa", "sb").alias("sa"), F.greatest("sa", "sb").alias("sb"), "a", "b")


def ball_stats(graph: Graph, ball: DataFrame, beta: float) -> DataFrame:
    """One row: balls, edges, cut edges, cut fraction over beta, largest radius, radius * beta / ln n."""
    n = max(2, graph.vertices.count())
    cut = crossing(graph, ball).agg(F.count(F.lit(1)).alias("cut_edges"))
    all_ = graph.edges.agg(F.count(F.lit(1)).alias("edges"))
    shape = ball.agg(F.countDistinct("source").alias("balls"), F.max("hop").alias("max_hop"))
    return shape.crossJoin(all_).crossJoin(cut).select("balls", "edges", "cut_edges", (F.col("cut_edges") / F.greatest("edges", F.lit(1)) / beta).alias("cut_over_beta"), "max_hop", (F.col("max_hop") * beta / math.log(n)).alias("radius_ratio"))
