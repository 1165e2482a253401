"""Decomposition and stored query structures against brute force on small random graphs."""

import random
from collections import defaultdict

import pytest

from lwgraph.operators import blocks, connect, decompose
from lwgraph.operators.oracles import BiconnectivityOracle, ConnectivityOracle, lowpoint_blocks
from lwgraph.plans.graph import CostMeter, Graph


def random_edges(seed, n=60, extra=25, cap=4):
    """A few bounded-degree components, some tiny."""
    rnd = random.Random(seed)
    deg, edges, at = defaultdict(int), [], 0
    for size in (n, 17, 5, 2):
        for i in range(1, size):
            j = rnd.choice([x for x in range(i) if deg[at + x] < cap])
            edges.append((at + i, at + j))
            deg[at + i] += 1
            deg[at + j] += 1
        for _ in range(extra * size // n):
            i, j = rnd.randrange(size), rnd.randrange(size)
            if i != j and deg[at + i] < cap and deg[at + j] < cap:
                edges.append((at + i, at + j))
                deg[at + i] += 1
                deg[at + j] += 1
        at += size
    return edges, list(range(at + 2))


def brute(edges, vertices):
    block, cut = lowpoint_blocks(edges)
    names, inc = {}, defaultdict(set)
    for n, (a, b) in enumerate(edges):
        names[block[n]] = min(names.get(block[n], (9e9, 0)), (min(a, b), max(a, b)))
        inc[a].add(block[n])
        inc[b].add(block[n])
    root = {v: v for v in vertices}

    def find(x, r):
        while r[x] != x:
            x = r[x]
        return x

    two = dict(root)
    for n, (a, b) in enumerate(edges):
        p, q = sorted((find(a, root), find(b, root)))
        root[q] = p
        if n not in cut:
            p, q = sorted((find(a, two), find(b, two)))
            two[q] = p
    bridges = {(min(edges[n]), max(edges[n])) for n in cut}
    return {"inc": inc, "comp": {v: find(v, root) for v in vertices}, "two": {v: find(v, two) for v in vertices}, "bridges": bridges, "ap": {v for v in vertices if len(inc[v]) > 1}, "blocks": len(set(block.values()))}


def graph_of(spark, edges, vertices):
    return Graph.of(spark.createDataFrame(edges, "x long, y long"), spark.createDataFrame([(v,) for v in vertices], "vid long")).fixed()


def test_lowpoint_on_worked_example():
    e = [(1, 2), (2, 4), (4, 7), (6, 7), (3, 6), (1, 3), (2, 6), (2, 5), (6, 8), (8, 9), (6, 9)]
    block, cut = lowpoint_blocks(e)
    assert {e[n] for n in cut} == {(2, 5)}
    assert len({block[n] for n in range(7)}) == 1 and len({block[8], block[9], block[10]}) == 1 and len(set(block.values())) == 3


def test_worked_decomposition(spark):
    """Letters a..l are 1..12; primaries d, e, g and k = 4: exactly b is added."""
    pairs = ["ac", "ag", "gk", "bc", "be", "ef", "bi", "bj", "fi", "dh", "dl", "jl", "hk"]
    n = {c: i + 1 for i, c in enumerate("abcdefghijkl")}
    g = graph_of(spark, [(n[p[0]], n[p[1]]) for p in pairs], list(n.values()))
    prim = spark.createDataFrame([(n[c],) for c in "deg"], "vid long")
    hops = decompose.next_hops(g, prim)
    second = decompose.split_clusters(hops, prim, 4)
    assert [r.vid for r in second.collect()] == [n["b"]]
    where = {r.vid: r.center for r in decompose.center_of(hops, prim.unionByName(second)).collect()}
    clusters = defaultdict(set)
    for v, c in where.items():
        clusters[c].add("abcdefghijkl"[v - 1])
    assert sorted(map("".join, map(sorted, clusters.values()))) == ["acgk", "bij", "dhl", "ef"]


@pytest.mark.parametrize("mode", ["recursive", "levelwise"])
def test_decomposition_is_valid(spark, mode):
    edges, vertices = random_edges(4)
    dec = decompose.decompose(graph_of(spark, edges, vertices), 5, 1, mode=mode)
    row = decompose.check_decomposition(dec).head()
    assert (row.lost, row.oversized, row.broken) == (0, 0, 0)
    all_ = {r.vid: r.center for r in dec.lookup().collect()}
    asked = spark.createDataFrame([(v,) for v in vertices[::7]], "vid long")
    assert {r.vid: r.center for r in decompose.lookup_center(dec, asked).collect()} == {v: all_[v] for v in vertices[::7]}


def test_connectivity_oracle(spark, tmp_path):
    edges, vertices = random_edges(5)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    o = ConnectivityOracle.build(g, k=5)
    got = {r.vid: r.comp for r in o.component().collect()}
    assert all((got[u] == got[v]) == (want["comp"][u] == want["comp"][v]) for u in vertices for v in vertices)
    o.save(f"file://{tmp_path}/o")
    again = ConnectivityOracle.load(g, f"file://{tmp_path}/o")
    assert {r.vid: r.comp for r in again.component().collect()} == got


@pytest.mark.parametrize("seed", [1, 2])
def test_biconnectivity_oracle(spark, seed):
    edges, vertices = random_edges(seed, n=40, extra=30)
    edges.append(edges[0])  # a copy
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    o = BiconnectivityOracle.build(g, k=4, seed=seed)
    assert {(r.a, r.b) for r in o.is_bridge().collect() if r.is_bridge} == want["bridges"]
    assert {r.vid for r in o.is_articulation().collect()} == want["ap"]
    assert o.block_count().head()[0] == want["blocks"]
    pairs = [(u * 1000 + v, u, v) for u in vertices for v in vertices[::3]]
    df = spark.createDataFrame(pairs, "qid long, u long, v long")
    same = {r.qid: r.same_block for r in o.same_block(df, batch=True).collect()}
    assert [p for p in pairs if same[p[0]] != (p[1] == p[2] or bool(want["inc"][p[1]] & want["inc"][p[2]]))] == []
    edge = {r.qid: r.same_edge_block for r in o.same_edge_block(df, batch=True).collect()}
    assert [p for p in pairs if edge[p[0]] != (want["two"][p[1]] == want["two"][p[2]])] == []


def test_methods_agree(spark):
    edges, vertices = random_edges(9)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    for method in (connect.components_star, connect.bfs_components, connect.recursive_contraction, lambda x: connect.components_lowwrite(x, beta=0.5)):
        assert {r.vid: r.comp for r in method(g).collect()} == want["comp"]
    bl = blocks.block_labelling(g, beta=0.5)
    assert {(r.a, r.b) for r in blocks.bridges(bl).collect()} == want["bridges"]
    assert {r.vid for r in blocks.articulation_points(bl).collect()} == want["ap"]
    assert {r.vid: r.comp for r in blocks.two_edge_components(bl).collect()} == want["two"]


def test_empty_and_degenerate(spark):
    g = Graph.of(spark.createDataFrame([(1, 1), (2, None)], "x long, y long"), spark.createDataFrame([(5,)], "vid long")).fixed()
    assert sorted(r.vid for r in g.vertices.collect()) == [1, 5] and g.edges.count() == 0
    assert sorted((r.vid, r.comp) for r in connect.components_lowwrite(g, beta=0.5).collect()) == [(1, 1), (5, 5)]


@pytest.mark.parametrize("seed", [3])
def test_lookup_needs_no_table_of_all_vertices(spark, seed):
    """All vertices are looked up from centers and arcs alone, also where no primary can be reached."""
    edges, vertices = random_edges(seed)
    meter = CostMeter("decomposition")
    dec = decompose.decompose(graph_of(spark, edges, vertices), 5, seed, meter=meter)
    want = {r.vid: r.center for r in dec.lookup().collect()}
    dec.hops = dec.implicit = None
    assert {r.vid: r.center for r in decompose.lookup_center(dec, dec.graph.vertices).collect()} == want
    # next hops and the tables of centers hold one row a vertex each
    assert sum(writes for _, stage, _, writes, _, _ in meter.rows if stage == "next hops") >= len(vertices) - 10
    assert meter.total()[1] >= 2 * len(vertices)
