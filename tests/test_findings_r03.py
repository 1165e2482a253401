"""What the findings of the third round were about, small enough to fail without a large table."""

from collections import Counter

import numpy as np
import pytest

from lwgraph import measures
from lwgraph.operators import blocks, decompose, local, searches
from lwgraph.operators.oracles import BiconnectivityOracle

from .test_in_one_task import ROWS, written  # noqa: F401
from .test_oracles import brute, graph_of, random_edges


FOLDER = "/root/testdata/sf0.001"


@pytest.mark.parametrize("order", ["vid", "hash"])
def test_look_ups_beyond_one_tasks_rows(spark, monkeypatch, written, order):  # noqa: F811
    """Arcs above the bound of one task are packed in pieces and searched by arrays, not in rounds over all questions; what is packed serves every k."""
    g = graph_of(spark, *random_edges(11, n=60, extra=15)).fixed()
    made = lambda k: decompose.decompose(g, k, 1, order=order)
    asked = lambda dec: ROWS(decompose.lookup_center(dec, g.vertices, costs=True))
    near = [asked(made(k)) for k in (4, 8)]
    monkeypatch.setattr(local, "ROWS", 3)
    monkeypatch.setattr(searches, "PIECE", 40)
    decs = [made(k) for k in (4, 8)]
    del written[:]
    assert [asked(dec) for dec in decs] == near
    assert "look" not in written and written.count("arcs") == 1 and decs[0].arcs.select("piece").distinct().count() > 2
    monkeypatch.setattr(searches, "HELD", 3)
    assert [asked(dec) for dec in decs] == near and "look" in written


def test_samples_beyond_one_tasks_rows(spark, monkeypatch, written):  # noqa: F811
    """Bridges of all samples come from arrays of places, not from rounds over their union."""
    near = ROWS(measures.w6_percolation_bridges(spark, FOLDER))
    monkeypatch.setattr(local, "ROWS", 100)
    del written[:]
    assert ROWS(measures.w6_percolation_bridges(spark, FOLDER)) == near and sum(r[2] for r in near) > 100
    assert "spots" in written and "tree" not in written


@pytest.mark.parametrize("seed", [1, 2])
def test_bridges_by_arrays(seed):
    edges, vertices = random_edges(seed, n=40, extra=12)
    many = Counter((min(e), max(e)) for e in edges if e[0] != e[1])
    names = sorted({v for e in many for v in e})
    a, b = (np.array([names.index(e[i]) for e in many], np.int32) for i in (0, 1))
    cut = local.bridge_arrays(a, b, np.array([n == 1 for n in many.values()]), len(names))
    assert {e for e, c in zip(many, cut, strict=True) if c} == set(brute(edges, vertices)["bridges"])


def test_walks_by_whole_trees(spark, monkeypatch, written):  # noqa: F811
    """The walk of the other split of cases deals whole trees of clusters to tasks where all clusters are too many for one, and goes in rounds only for a tree that is."""
    parts = [random_edges(s, n=20, extra=10) for s in (1, 2, 3)]
    edges = [(a + 100 * i, b + 100 * i) for i, (es, _) in enumerate(parts) for a, b in es]
    vertices = [v + 100 * i for i, (_, vs) in enumerate(parts) for v in vs]
    o = BiconnectivityOracle.build(graph_of(spark, edges, vertices), k=4, seed=1)
    some = sorted(vertices)[::3]
    pairs = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate((u, v) for u in some for v in some)], "qid long, u long, v long")
    want = ROWS(o.same_block(pairs, batch=True))
    for rows, steps in ((local.ROWS, 2), (60, 2), (1, 3)):
        monkeypatch.setattr(local, "ROWS", rows)
        del written[:]
        assert ROWS(o.same_block_step_by_step(pairs)) == want
        assert (written.count("step") <= steps) == (rows > 1)


def test_labelling_by_whole_components(spark, monkeypatch, written):  # noqa: F811
    """Components that are too many for a task are labelled by several, numbered as one task does; only a component too large for one takes rounds."""
    parts = [random_edges(s, n=20, extra=10) for s in (1, 2, 3)]
    edges = [(a + 100 * i, b + 100 * i) for i, (es, _) in enumerate(parts) for a, b in es]
    g = graph_of(spark, edges, [v + 100 * i for i, (_, vs) in enumerate(parts) for v in vs]).fixed()

    def made():
        bl = blocks.whole_labelling(g)
        return ROWS(bl.forest), ROWS(bl.label), ROWS(bl.head)

    near = made()
    monkeypatch.setattr(blocks, "SHARE", 8)
    monkeypatch.setattr(local, "ROWS", 40)
    del written[:]
    assert made() == near and "labelled" in written and "circuit" not in written
    monkeypatch.setattr(local, "ROWS", 2)
    blocks.whole_labelling(g)
    assert "circuit" in written
