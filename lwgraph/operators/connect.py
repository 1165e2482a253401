"""Connectivity and spanning forests: the low-write method, its inner forest and the baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.adjacency import adjacency
from ..plans.graph import CostMeter, Graph
from ..plans.scratch import discard, materialize, measured, watched
from . import local
from .balls import ball_partition, ball_trees, crossing
from .contraction import contract_components, flatten


def forest_of(edges: DataFrame, meter: CostMeter | None = None, max_rounds: int = 64) -> tuple[DataFrame, DataFrame]:
    """((vid, comp), forest (ra, rb)) of edges (a, b) that stand for original edges (ra, rb).

    Each round hooks every vertex onto its least neighbour when that is smaller, keeps the
    representative edge of each hook, and contracts; the last ``local.ROWS`` edges take one task."""
    wanted, looked = watched(edges.filter("a <> b"))
    live, seen = measured(wanted.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.min(F.struct("ra", "rb")).alias("rep")), "forest-edges")
    if meter:
        meter.add("inner forest", ops=looked.rows, writes=seen["rows"])
    ends = live.select(F.explode(F.array("a", "b")).alias("vid")).distinct()
    label, trees, left = None, None, live.count()
    for _ in range(max_rounds):
        if left == 0:
            break
        if left <= local.ROWS:
            done, told = measured(local.local_forest(live.select("a", "b", "rep.ra", "rep.rb")), "forest-end")
            used, root, rest, writes, ops = done.filter("vid is null").select("ra", "rb"), done.filter("vid is not null").select("vid", "root"), None, told["rows"], left
            left = 0
        else:
            arcs, looked = watched(live.select(F.explode(F.array(F.struct(F.col("a").alias("vid"), F.col("b").alias("other")), F.struct(F.col("b").alias("vid"), F.col("a").alias("other")))).alias("arc"), "rep").select("arc.*", "rep"))
            hooks, told = measured(arcs.groupBy("vid").agg(F.min(F.struct("other", "rep")).alias("w")).select("vid", F.col("w.other").alias("other"), F.col("w.rep").alias("rep")), "hooks")
            used = hooks.filter("other < vid").select("rep.*")
            root = flatten(hooks.select("vid", F.least("vid", "other").alias("parent")))
            x, y = root.select(F.col("vid").alias("a"), F.col("root").alias("xa")), root.select(F.col("vid").alias("b"), F.col("root").alias("xb"))
            moved = live.join(x, "a").join(y, "b").filter("xa <> xb").groupBy(F.least("xa", "xb").alias("a"), F.greatest("xa", "xb").alias("b")).agg(F.min("rep").alias("rep"))
            rest = materialize(moved, "forest-edges")
            ops, left = looked.rows + left, rest.count()
            writes = 2 * told["rows"] + left  # hooks, their roots, and the edges that survive
        trees = used if trees is None else trees.unionByName(used)
        live = rest
        if label is None:
            label = root
        else:
            step = root.select(F.col("vid").alias("root"), F.col("root").alias("next"))
            label, told = measured(label.join(step, "root", "left").select("vid", F.coalesce("next", "root").alias("root")), "labels")
            writes += told["rows"]
        if meter:
            meter.add("inner forest", ops=ops, writes=writes, rounds=1)
    if left:
        raise RuntimeError("too many contraction rounds")
    if label is None:
        return ends.select("vid", F.col("vid").alias("comp")), edges.select("ra", "rb").limit(0)
    return ends.join(label, "vid", "left").select("vid", F.coalesce("root", "vid").alias("comp")), trees


def components_star(graph: Graph, meter: CostMeter | None = None) -> DataFrame:
    """(vid, comp) by the inner method alone."""
    comp, _ = forest_of(graph.edges.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb")), meter)
    return graph.vertices.join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp"))


def forest_boruvka(graph: Graph) -> DataFrame:
    """Spanning forest (a, b) by the inner method alone."""
    _, trees = forest_of(graph.edges.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb")))
    return trees.select(F.col("ra").alias("a"), F.col("rb").alias("b"))


def components_lowwrite(graph: Graph, *, omega: float = 4.0, beta: float | None = None, seed: int = 0, meter: CostMeter | None = None, want_forest: bool = False, **options):
    """(vid, comp): balls with beta = 1/omega, contraction of the few crossing edges, inner forest, relabel.

    With ``want_forest`` also the spanning forest: ball trees plus one original edge for each inner tree edge."""
    beta = beta if beta is not None else min(0.9, 1.0 / omega)
    ball = ball_partition(graph, beta, seed, meter=meter, parents=want_forest, **options)
    met, looked = watched(crossing(graph, ball))
    cut, seen = measured(met.groupBy("sa", "sb").agg(F.min(F.struct("a", "b")).alias("rep")).select(F.col("sa").alias("a"), F.col("sb").alias("b"), F.col("rep.a").alias("ra"), F.col("rep.b").alias("rb")), "contracted")
    if meter:
        meter.add("contraction", ops=graph.edges.count() + looked.rows, writes=seen["rows"], rounds=1)
    comp, inner = forest_of(cut, meter)
    joined = ball.join(comp.withColumnRenamed("vid", "source"), "source", "left").select("vid", F.coalesce("comp", "source").alias("ball_comp"))
    least = joined.groupBy("ball_comp").agg(F.min("vid").alias("comp"))
    out = joined.join(least, "ball_comp").select("vid", "comp")
    if not want_forest:
        return out
    return out, ball_trees(ball).unionByName(inner.select(F.col("ra").alias("a"), F.col("rb").alias("b")))


def spanning_forest(graph: Graph, **options) -> DataFrame:
    """Spanning forest (a, b) of the low-write method."""
    return components_lowwrite(graph, want_forest=True, **options)[1]


# --- baselines --------------------------------------------------------------------------------


def bfs_components(graph: Graph, meter: CostMeter | None = None, max_rounds: int = 100_000) -> DataFrame:
    """Level-by-level search from every component's least vertex, unknown at the start: the least label spreads over a frontier.

    A vertex is written whenever its label falls, at least once; rounds grow like the diameter."""
    return _propagated(graph, "breadth-first", meter, max_rounds, frontier_only=True)


def label_propagation(graph: Graph, meter: CostMeter | None = None, max_rounds: int = 100_000) -> DataFrame:
    """Least-label propagation over all edges every round, all labels rewritten."""
    return _propagated(graph, "propagation", meter, max_rounds, frontier_only=False)


def _propagated(graph: Graph, stage: str, meter: CostMeter | None, max_rounds: int, *, frontier_only: bool) -> DataFrame:
    with adjacency(graph) as arcs:
        label, seen = measured(graph.vertices.select("vid", F.col("vid").alias("comp"), F.lit(1).cast("long").alias("new")), "labels")
        if meter:
            meter.add(stage, writes=seen["rows"])
        for _ in range(max_rounds):
            front = label.filter("new = 1") if frontier_only else label
            sent, looked = watched(front.select(F.col("vid").alias("src"), "comp").join(arcs.select("src", "dst"), "src"))
            offers = sent.groupBy("dst").agg(F.min("comp").alias("offer")).withColumnRenamed("dst", "vid")
            falls = F.coalesce(F.col("offer") < F.col("comp"), F.lit(False)).cast("long")
            then, seen = measured(label.join(offers, "vid", "left").select("vid", F.least("comp", "offer").alias("comp"), falls.alias("new")), "labels", new=F.col("new"))
            if meter:
                meter.add(stage, ops=looked.rows, writes=seen["new"] if frontier_only else seen["rows"], rounds=1)
            discard(label)
            label = then
            if seen["new"] == 0:
                return label.select("vid", "comp")
    raise RuntimeError("label propagation did not settle")


def recursive_contraction(graph: Graph, beta: float = 0.2, seed: int = 0, meter: CostMeter | None = None) -> DataFrame:
    """Balls with constant beta again and again; every level's edges are written out."""
    label = graph.vertices.select("vid", F.col("vid").alias("at"))
    now, level = graph.fixed(), 0
    if meter:
        meter.add("contraction", ops=now.edges.count(), writes=now.edges.count())
    while True:
        ball = ball_partition(now, beta, seed + level, meter=meter, parents=False)
        step = ball.select(F.col("vid").alias("at"), "source")
        label, seen = measured(label.join(step, "at").select("vid", F.col("source").alias("at")), "levels")
        cut, looked = watched(crossing(now, ball))
        now = Graph(ball.select(F.col("source").alias("vid")).distinct(), cut.select(F.col("sa").alias("a"), F.col("sb").alias("b")).groupBy("a", "b").agg(F.count(F.lit(1)).cast("int").alias("mult"))).fixed()
        m = now.edges.count()
        if meter:
            meter.add("contraction", ops=looked.rows, writes=seen["rows"] + m, rounds=1)
        level += 1
        if m == 0:
            break
    least = label.groupBy("at").agg(F.min("vid").alias("comp"))
    return label.join(least, "at").select("vid", "comp")


def union_find(graph: Graph, driver_max: int = 200_000) -> DataFrame:
    """Sequential union-find on the driver; of a graph with more than ``driver_max`` edges, over the edges that rounds of contraction leave."""

    def on_driver(edges: DataFrame) -> DataFrame:
        root: dict[int, int] = {}

        def find(x):
            while root.setdefault(x, x) != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for r in edges.select("a", "b").collect():
            p, q = sorted((find(r["a"]), find(r["b"])))
            root[q] = p
        return edges.sparkSession.createDataFrame([(v, find(v)) for v in root], "vid long, root long")

    comp = contract_components(graph.edges, rows=driver_max, end=on_driver)
    return graph.vertices.join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp"))


def partition_forest(graph: Graph, block: int = 1 << 18) -> DataFrame:
    """Edges (a, b) left after each partition reduced its own to a forest, ``block`` edges at a time: same components, far fewer rows before any exchange."""
    import numpy as np
    import pyarrow as pa

    def reduced(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        _, kept = local.forest_arrays(at[: len(a)], at[len(a) :], len(names))
        return a[kept], b[kept]

    def run(batches):
        a = b = np.zeros(0, np.int64)
        for batch in batches:
            a, b = np.concatenate([a, batch.column("a").to_numpy()]), np.concatenate([b, batch.column("b").to_numpy()])
            if len(a) > block:
                a, b = reduced(a, b)
                if len(a) > block // 2:  # the forest itself is large: pass it on and start again
                    yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])
                    a = b = np.zeros(0, np.int64)
        a, b = reduced(a, b)
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return graph.edges.select("a", "b").mapInArrow(run, "a long, b long")


# --- answers ----------------------------------------------------------------------------------


def component_sizes(comp: DataFrame) -> DataFrame:
    return comp.groupBy("comp").agg(F.count(F.lit(1)).alias("size"))


def connected(comp: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, connected); unknown vertices give null."""
    x, y = comp.select(F.col("vid").alias("u"), F.col("comp").alias("cu")), comp.select(F.col("vid").alias("v"), F.col("comp").alias("cv"))
    return pairs.join(x, "u", "left").join(y, "v", "left").select("qid", (F.col("cu") == F.col("cv")).alias("connected"))
