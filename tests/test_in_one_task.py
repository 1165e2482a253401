"""Steps that end in one task give what their rounds give, and leave no rounds to small graphs."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from lwgraph.operators import decompose, local
from lwgraph.operators.bfs import levels
from lwgraph.operators.blocks import block_labelling, bridges, canonical_blocks, root_forest, whole_labelling
from lwgraph.operators.connect import forest_boruvka
from lwgraph.operators.oracles import BiconnectivityOracle, _facts, lowpoint_blocks
from lwgraph.operators.trees import rootfix
from lwgraph.plans import scratch

from .test_oracles import brute, graph_of, random_edges

ROWS = lambda df: sorted(map(tuple, df.collect()))


@pytest.fixture
def written(monkeypatch):
    """Names of the scratch tables that are written."""
    names, path = [], scratch.new_scratch_path
    monkeypatch.setattr(scratch, "new_scratch_path", lambda spark, name: names.append(name) or path(spark, name))
    return names


def both(monkeypatch, make):
    near = make()
    monkeypatch.setattr(local, "ROWS", 3)
    return near, make()


@pytest.mark.parametrize("mode", ["recursive", "recursive_children", "levelwise"])
def test_decomposition_in_trees_and_in_rounds(spark, monkeypatch, mode):
    g = graph_of(spark, *random_edges(11, n=60, extra=15))

    def make():
        dec = decompose.decompose(g, 4, 1, mode=mode, order="hash" if mode == "recursive_children" else "vid")
        return ROWS(dec.hops), ROWS(dec.centers), ROWS(dec.lookup()), ROWS(decompose.lookup_center(dec, dec.graph.vertices, costs=True))

    near, far = both(monkeypatch, make)
    assert near == far


def test_forest_and_levels_in_one_task(spark, monkeypatch):
    g = graph_of(spark, *random_edges(3, n=50, extra=10))
    tree = forest_boruvka(g)
    near, far = both(monkeypatch, lambda: (ROWS(root_forest(g, tree)), ROWS(levels(g, g.vertices.filter("vid % 9 = 0"))),
                                           ROWS(rootfix(root_forest(g, tree).select("vid", "parent", "depth"), "depth", "most"))))
    assert near == far


def test_an_oracle_of_a_small_graph_has_few_writes(spark, written):
    """Search, split, look-up and walks up the clusters took a write a round."""
    edges, vertices = random_edges(1, n=40, extra=30)
    o = BiconnectivityOracle.build(graph_of(spark, edges, vertices), k=4, seed=1)
    assert max(written.count(n) for n in ("levels", "center", "rootfix")) <= 4 and "clusters" not in written[: written.index("quotient-once")]
    facts = scratch.materialize(o.local_facts(), "facts")
    assert {r.vid for r in o.cut_block_tree(facts).collect()} == brute(edges, vertices)["ap"]  # the facts outlive the numbering
    assert o.edge_block(facts=facts).count() == graph_of(spark, edges, vertices).edges.count()


def test_facts_of_many_clusters_at_once():
    """The views of a block are labelled as one graph; every cluster gets what a search of its own finds."""
    rng, rows, views = random.Random(5), [], {}
    for cluster in range(10, 40):
        points = rng.sample(range(100), rng.randint(1, 6)) + [-1 - p for p in rng.sample(range(50), rng.randint(0, 3))]
        tree = [(points[i], points[rng.randrange(i)]) for i in range(1, len(points))]
        edges = tree + [tuple(rng.sample(points, 2)) for _ in range(rng.randint(0, 4)) if len(points) > 1]
        lone = [p for p in points if p < 0 and sum(p in e for e in edges) == 1]  # a parent's port has one block
        views[cluster] = (points, edges, lone[0] if lone else None)
        rows += [(cluster, x, y, 1, n, n + 1, None) for n, (x, y) in enumerate(edges)] + [(cluster, p, None, -2, None, None, None) for p in points if p >= 0]
        rows.append((cluster, lone[0] if lone else min(p for p in points if p >= 0), None, -1, None, None, None))
    rng.shuffle(rows)
    names = ("cluster", "x", "y", "origin", "ea", "eb", "kid")
    told = _facts(pa.table({n: pa.array(c, pa.int32() if n == "origin" else pa.int64()) for n, c in zip(names, zip(*rows, strict=True), strict=True)})).to_pylist()
    for cluster, (points, edges, port) in views.items():
        mine = [r for r in told if r["cluster"] == cluster]
        block, cut = lowpoint_blocks(edges)
        found = {r["ea"]: r for r in mine if r["kind"] == "edge"}
        assert {n: (r["x"], r["y"]) for n, r in found.items()} == dict(enumerate(edges)) and {n for n, r in found.items() if r["edge_open"]} == cut
        assert {(block[n], r["block"]) for n, r in found.items()} == {(block[n], found[n]["block"]) for n in {block[m]: m for m in block}.values()}
        assert sorted({r["block"] for r in found.values()}) == list(range(len(set(block.values()))))
        lies = {(p, found[n]["block"]) for n, e in enumerate(edges) for p in e}
        assert sorted((r["x"], r["block"]) for r in mine if r["kind"] == "member") == sorted(lies)
        top = {b for p, b in lies if p == port}
        comp = {p: p for p in points}
        for _ in points:
            for n, (x, y) in enumerate(edges):
                if n not in cut:
                    comp[x] = comp[y] = min(comp[x], comp[y])
        assert sorted((r["x"], r["y"], r["open"], r["edge_open"]) for r in mine if r["kind"] == "point") == \
            sorted((p, comp[p], any((p, b) in lies for b in top), port is not None and comp[p] == comp[port]) for p in points)
        assert all(r["open"] == (r["block"] in top) for r in mine if r["kind"] in ("edge", "member"))
        (count,) = [r for r in mine if r["kind"] == "count"]
        assert (count["blocks"], count["block"]) == (len(set(block.values())) - (port is not None), min(top) if top else None)


@pytest.mark.parametrize("seed", range(20))
def test_labelling_and_bridges_in_arrays(seed):
    rng = random.Random(seed)
    n, m = rng.randint(1, 40), rng.randint(0, 60)
    edges = sorted({tuple(sorted(rng.sample(range(n), 2))) for _ in range(m)}) if n > 1 else []
    a, b = (np.array([e[i] for e in edges], np.int64) for i in (0, 1))
    root, chosen = local.forest_arrays(a, b, n)
    made = local.rooted_arrays(a[chosen], b[chosen], root)
    told = local.labelled_arrays(a, b, made["parent"], made["idx"], made["size"])
    block, _ = lowpoint_blocks(edges)
    lower = [y if made["idx"][x] <= made["idx"][y] < made["idx"][x] + made["size"][x] else x for x, y in edges]
    pairs = {(block[i], int(told["block"][v])) for i, v in enumerate(lower)}
    assert len(pairs) == len({p for p, _ in pairs}) == len({q for _, q in pairs})
    for q in {q for _, q in pairs}:
        inside = np.flatnonzero(told["block"] == q)
        assert told["members"][q] == len(inside) and told["head"][q] == made["parent"][inside[np.argmin(made["idx"][inside])]]


def test_a_small_labelling_is_one_write(spark, monkeypatch, written):
    """Edges beside the tree, reaches, ranges, separating bits, labels and heads took a write each."""
    g = graph_of(spark, *random_edges(7, n=40, extra=25))
    forest = root_forest(g, forest_boruvka(g))

    def make():
        written.clear()
        bl = block_labelling(g, forest)
        return len(written), ROWS(canonical_blocks(bl)), ROWS(bl.head), ROWS(bl.label), ROWS(bl.forest.select(*sorted(bl.forest.columns)).na.fill(-1).withColumn("separating", F.coalesce("separating", F.lit(False))))

    near, far = both(monkeypatch, make)
    assert near[0] == 1 and near[1:] == far[1:]


def test_the_facts_of_all_clusters_are_written_once(spark, written):
    o = BiconnectivityOracle.build(graph_of(spark, *random_edges(2, n=40, extra=30)), k=4, seed=1)
    o.is_bridge().count(), o.edge_block().count(), o.cut_block_tree().count(), o.two_edge_components().count()
    assert written.count("facts") == 1


def test_bridges_of_many_graphs(spark):
    """Two samples in ranges of their own get the bridges of their union's labelling."""
    graphs = [random_edges(s, n=30, extra=8) for s in (3, 4)]
    g = graph_of(spark, [(a + 1000 * i, b + 1000 * i) for i, (e, _) in enumerate(graphs) for a, b in e], [v + 1000 * i for i, (_, vs) in enumerate(graphs) for v in vs])
    found = ROWS(local.local_bridges(g.edges, F.floor(F.col("a") / 1000)))
    assert sorted((a, b) for _, a, b in found) == ROWS(bridges(whole_labelling(g))) and {k for k, _, _ in found} == {0, 1} and all(a // 1000 == k for k, a, _ in found)


def test_the_walk_by_steps_is_one_write(spark, monkeypatch, written):
    """It wrote the pairs once a step."""
    edges, vertices = random_edges(6, n=40, extra=25)
    o = BiconnectivityOracle.build(graph_of(spark, edges, vertices), k=4, seed=1)
    pairs = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate((u, v) for u in vertices[:12] for v in vertices)], "qid long, u long, v long")

    def make():
        written.clear()
        return ROWS(o.same_block_step_by_step(pairs)), written.count("step")

    near, far = both(monkeypatch, make)
    assert near[0] == far[0] and near[1] == 2 < far[1]
