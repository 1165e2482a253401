"""Searches by arrays tell what each question's own search would, and clusters are searched for once."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from lwgraph.operators import decompose, local, searches
from lwgraph.operators.oracles import BiconnectivityOracle
from lwgraph.plans import scratch

from .test_oracles import brute, graph_of, random_edges

ROWS = lambda df: sorted(map(tuple, df.collect()))


@pytest.fixture
def written(monkeypatch):
    """Names of the scratch tables that are written."""
    names, path = [], scratch.new_scratch_path
    monkeypatch.setattr(scratch, "new_scratch_path", lambda spark, name: names.append(name) or path(spark, name))
    return names


def one_by_one(near, kinds, q):
    """(center, visited) of one vertex: levels outward up to one with a primary, then the least way back along them."""
    levels, seen = [[q]], {q}
    while levels[-1] and not any(kinds[v] == 2 for v in levels[-1]):
        levels.append(sorted({w for v in levels[-1] for w in near[v]} - seen))
        seen.update(levels[-1])
    if not levels[-1]:
        return min(seen), len(seen)
    leads = [{v for v in levels[-1] if kinds[v] == 2}]
    for level in levels[-2::-1]:
        leads.insert(0, {v for v in level if leads[0] & set(near[v])})
    at, depth = q, 0
    while not kinds[at]:
        depth += 1
        at = min(leads[depth] & set(near[at]))
    return at, len(seen)


@pytest.mark.parametrize(("chunk", "most"), [(1 << 13, 1 << 23), (7, 1 << 23), (50, 20)])
def test_searches_together_are_those_one_by_one(monkeypatch, chunk, most):
    monkeypatch.setattr(searches, "CHUNK", chunk)
    monkeypatch.setattr(searches, "MOST", most)
    for seed in range(40):
        r = random.Random(seed)
        n = r.randint(2, 60)
        near = {3 * v: set() for v in range(n)}
        for _ in range(r.randint(1, 2 * n)):
            x, y = r.sample(sorted(near), 2)
            near[x].add(y)
            near[y].add(x)
        kinds = {v: r.choice([0, 0, 0, 0, 1, 2]) for v in near}
        lone, names = [v for v in near if not near[v]], np.array([v for v in near if near[v]])
        around = [np.searchsorted(names, sorted(near[v])) for v in names.tolist()]
        arrays = [names, np.cumsum([0, *map(len, around)]), np.concatenate(around).astype(np.int32), np.array([kinds[v] for v in names.tolist()], np.int8)]
        told = searches.looked_up(np.array(sorted(near)), arrays).to_pylist()
        want = {v: (v, 1) if v in lone else one_by_one(near, kinds, v) for v in near}
        assert {t["vid"]: (t["center"], t["visited"]) for t in told} == want


def test_clusters_are_searched_for_once(spark, monkeypatch, written):
    """Neighbours of clusters need no look-up but those of the search for the members; in rounds and in tasks they are the same."""
    edges, vertices = random_edges(21, n=70, extra=20)
    dec = decompose.decompose(graph_of(spark, edges, vertices), 4, 1)
    asked = dec.lookup().select("center").distinct().filter(F.col("center") % 3 > 0)
    written.clear()
    near = ROWS(decompose.quotient_neighbors(dec, asked))
    assert not {"looked-up", "members-near"} & {*written} and written.count("met") == 1
    members = ROWS(decompose.members_of(dec, asked))
    keys = {r.center for r in asked.collect()}
    assert near == [r for r in ROWS(decompose.quotient_neighbors(dec)) if r[0] in keys]
    assert members == [r for r in ROWS(decompose.members_of_all(dec)) if r[0] in keys]
    monkeypatch.setattr(local, "ROWS", 3)
    assert near == ROWS(decompose.quotient_neighbors(dec, asked)) and members == ROWS(decompose.members_of(dec, asked))


def test_clusters_of_pairs_are_opened_once(spark, written):
    """Both answers of a few pairs come from one look-up and one set of cluster views, whose far ends need no look-up of their own."""
    edges, vertices = random_edges(22, n=60, extra=15)
    o = BiconnectivityOracle.build(graph_of(spark, edges, vertices), k=4, seed=1)
    pairs = spark.createDataFrame([(i, vertices[i], vertices[(7 * i + 3) % len(vertices)]) for i in range(0, len(vertices), 4)], "qid long, u long, v long")
    written.clear()
    got = ROWS(o.same_blocks(pairs))
    assert written.count("pair-facts") == written.count("looked-up") == written.count("met") == 1
    want = brute(edges, vertices)
    for q, same, same_edge in got:
        u, v = vertices[q], vertices[(7 * q + 3) % len(vertices)]
        assert same == (u == v or bool(want["inc"][u] & want["inc"][v])) and same_edge == (want["two"][u] == want["two"][v])
    assert len(got) == pairs.count() and got == ROWS(o.same_blocks(pairs, batch=True))


def test_both_saved_oracles_stand_on_one_decomposition(spark, written):
    from lwgraph import measures

    assert measures.s4_saved_oracles(spark, "/root/testdata/sf0.001").head()[0] == 0 and written.count("secondaries") == 1


def test_small_tables_leave_other_views_alone(spark, monkeypatch):
    """A query of one view makes no pass over all of them, whatever the size of the tables."""
    from lwgraph import workloads

    union = workloads.union_of_views
    asked = []
    monkeypatch.setattr(workloads, "union_of_views", lambda s, d, names=workloads.PROFILED: asked.append(names) or union(s, d, names))
    monkeypatch.setattr(workloads, "_KEPT", {})
    workloads.QUERIES["w_articulation_conversation_chain"](spark, "/root/testdata/sf0.001").collect()
    assert asked == [("conversation_chain",)]


def test_the_mesh_is_written_once(spark, monkeypatch, written):
    from lwgraph import extras, workloads

    monkeypatch.setattr(workloads, "_KEPT", {})
    for k in (4, 8):
        extras.mesh_decomposition(spark, "/root/testdata/sf0.001", k=k)
    assert written.count("graph-edges") == 1
