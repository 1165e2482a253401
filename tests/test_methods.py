"""Building blocks of the methods, with small bounds so that every distributed step runs, against plain counterparts."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from lwgraph import workloads
from lwgraph.operators import blocks, connect, decompose, degree, local, trees
from lwgraph.operators.balls import ball_partition
from lwgraph.operators.bfs import levels
from lwgraph.operators.joins import broadcast_under, guarded_cross, range_join
from lwgraph.operators.oracles import BiconnectivityOracle, ConnectivityOracle
from lwgraph.plans import scratch
from lwgraph.plans.adjacency import adjacency
from lwgraph.plans.graph import CostMeter, Graph, ScopeError
from lwgraph.plans.solve import solve
from lwgraph.sources.files import read_edges, register, write_edges

from .test_oracles import brute, graph_of, random_edges


@pytest.fixture
def far_apart(monkeypatch):
    """No step may end in one task."""
    monkeypatch.setattr(local, "ROWS", 3)


def test_forests_in_arrays():
    rng = np.random.default_rng(1)
    for n in (1, 2, 30):
        u, v = rng.integers(0, n, 40), rng.integers(0, n, 40)
        root, chosen = local.forest_arrays(u, v, n)
        want = list(range(n))
        for _ in range(n):
            for a, b in zip(u, v, strict=True):
                want[a] = want[b] = min(want[a], want[b])
        assert root.tolist() == want and chosen.sum() == n - len(set(want))


def test_contraction_without_a_local_end(spark, far_apart):
    edges, vertices = random_edges(12)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    comp, tree = connect.components_lowwrite(g, beta=0.5, want_forest=True)
    assert {r.vid: r.comp for r in comp.collect()} == want["comp"]
    assert tree.count() == len(vertices) - len(set(want["comp"].values()))
    assert {r.vid: r.comp for r in connect.components_star(Graph(g.vertices, tree)).collect()} == want["comp"]


def test_ranks_of_lists(spark, far_apart):
    rnd = random.Random(2)
    links, want, ids = [], {}, rnd.sample(range(1000), 60)
    for part in (ids[:40], ids[40:41], ids[41:]):
        for at, i in enumerate(part):
            links.append((i, part[at + 1] if at + 1 < len(part) else None, 1 if at + 1 < len(part) else 0))
            want[i] = len(part) - 1 - at
    got = blocks.list_rank(spark.createDataFrame(links, "id long, next long, step long"), spread=3)
    assert {r.id: r.left for r in got.collect()} == want


def test_extremes_over_ranges(spark, far_apart):
    rng = np.random.default_rng(3)
    lo, hi = rng.integers(0, 99, 90), rng.integers(0, 99, 90)
    rows = spark.createDataFrame([(i, int(a), int(b)) for i, (a, b) in enumerate(zip(lo, hi, strict=True))], "idx long, lo long, hi long")
    asked = [(k, *sorted(map(int, rng.integers(0, 90, 2)))) for k in range(80)]
    got = {r.id: (r.lo, r.hi) for r in trees.range_extremes(rows, spark.createDataFrame(asked, "id long, first long, last long"), block=4).collect()}
    assert got == {k: (lo[a : b + 1].min(), hi[a : b + 1].max()) for k, a, b in asked}


def test_common_ancestors(spark, far_apart):
    rnd = random.Random(4)
    up = {i: rnd.randrange(max(0, i - 3), i) if i not in (0, 20) else None for i in range(30)}
    g = graph_of(spark, [(i, p) for i, p in up.items() if p is not None], list(up))
    forest = blocks.root_forest(g, g.edges.select("a", "b"))
    parents = {r.vid: r.parent for r in forest.collect()}
    assert parents == up

    def way(v):
        return [v] if up[v] is None else [v, *way(up[v])]

    pairs = [(u * 100 + v, u, v) for u in up for v in up]
    got = {r.qid: r.lca for r in trees.lca(forest, spark.createDataFrame(pairs, "qid long, u long, v long")).collect()}
    assert all(got[q] == next((x for x in way(u) if x in way(v)), None) for q, u, v in pairs)


def test_edge_array_relates_edges(spark):
    """The classical method names blocks like the labelling does, and stores one row an edge."""
    edges, vertices = random_edges(6, n=40, extra=20)
    edges.append(edges[3])
    g, meter = graph_of(spark, edges, vertices), CostMeter("edge array")
    rows = {(r.a, r.b): r.block for r in blocks.edge_array_baseline(g, meter=meter).collect()}
    want = {(r.a, r.b): (r.block_a, r.block_b) for r in blocks.canonical_blocks(blocks.block_labelling(g, beta=0.5)).collect()}
    assert rows.keys() == want.keys() and len(set(rows.values())) == len(set(want.values())) == len(set(zip(rows.values(), (want[e] for e in rows), strict=True)))
    assert [w for _, stage, _, w, _, _ in meter.rows if stage == "edge array"][0] >= len(rows)


def test_levels_orders_and_meters(spark):
    edges, vertices = random_edges(7)
    g, meter = graph_of(spark, edges, vertices), CostMeter()
    sources = g.vertices.filter("vid % 9 = 0")
    plain = {r.vid: (r.hop, r.parent) for r in levels(g, sources, meter=meter).collect()}
    other = {r.vid: (r.hop, r.parent) for r in levels(g, sources, order="hash").collect()}
    assert {v: h for v, (h, _) in plain.items()} == {v: h for v, (h, _) in other.items()} and plain != other
    ops, writes, rounds = meter.total()
    degree_sum = sum(2 if a != b else 0 for a, b in {(min(e), max(e)) for e in edges})
    reached = {v for v in plain}
    assert writes == len(reached) and 0 < ops <= degree_sum and rounds == max(h for h, _ in plain.values()) + 1


def test_aggregates_of_rounds_need_no_sort(spark):
    """A level's least neighbour goes through hash aggregates; a least struct would sort."""
    rows = spark.range(100).select((F.col("id") % 7).alias("dst"), F.col("id").alias("src"), (F.col("id") * 2).alias("source"))
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "SortAggregate" not in plan(rows.groupBy("dst").agg(F.min_by("src", F.col("src")), F.min_by("source", F.col("src"))))
    assert "SortAggregate" in plan(rows.groupBy("dst").agg(F.min(F.struct("src", "source"))))


def test_bucketed_lists_stay_where_they_are(spark):
    g = graph_of(spark, [(i, i + 1) for i in range(50)], list(range(51)))
    with adjacency(g) as lists:
        assert "Exchange" not in lists.groupBy("src").count()._jdf.queryExecution().executedPlan().toString()
        name = lists._jdf.queryExecution().analyzed().toString().split("lw_adjacency_")[1][:12]
    assert not spark.catalog.tableExists(f"lw_adjacency_{name}")


def test_stored_messages_and_tie_rules_give_balls(spark):
    edges, vertices = random_edges(8)
    g, stored, lean = graph_of(spark, edges, vertices), CostMeter(), CostMeter()
    one = ball_partition(g, 0.5, 2, meter=lean).select("vid", "source", "hop").collect()
    two = ball_partition(g, 0.5, 2, materialize_messages=True, meter=stored).select("vid", "source", "hop").collect()
    assert sorted(one) == sorted(two) and {r.vid for r in one} == set(vertices) and stored.total()[1] > lean.total()[1]
    by_vid = {r.vid: r for r in ball_partition(g, 0.5, 2, tie_rule="fraction").collect()}
    near = {(min(a, b), max(a, b)) for a, b in edges}
    for r in by_vid.values():
        if r.parent is not None:
            assert (min(r.vid, r.parent), max(r.vid, r.parent)) in near and by_vid[r.parent].source == r.source and by_vid[r.parent].hop == r.hop - 1
        else:
            assert r.source == r.vid and r.hop == 0


@pytest.mark.parametrize("base", [0, 9 * 10**12, -50, 2**61])
def test_expansion_keeps_answers_at_any_id(spark, base):
    star = [(base, base + i) for i in range(1, 40)] + [(base + 5, base + 6), (base + 60, base + 61)]
    g = graph_of(spark, star, [base + 70])
    wide, names = degree.expand(g, 4, positions="stored")
    wide, names = wide.fixed(), scratch.materialize(names, "names")
    assert wide.max_degree() <= 6 and wide.expanded
    comp = {r.vid - base: r.comp - base for r in degree.project_components(connect.components_star(wide), names).collect()}
    assert comp == {**dict.fromkeys(range(40), 0), 60: 60, 61: 60, 70: 70}
    bl = blocks.block_labelling(wide, beta=0.5)
    cut = {(r.a - base, r.b - base) for r in degree.project_edges(blocks.bridges(bl), names).collect()}
    assert cut == {(0, i) for i in range(1, 40) if i not in (5, 6)} | {(60, 61)}
    for ask in (lambda: blocks.articulation_points(bl), lambda: blocks.edge_block(bl, wide.edges), lambda: BiconnectivityOracle.build(wide, k=4)):
        with pytest.raises(ScopeError):
            ask()


@pytest.mark.parametrize(("omega", "bound", "question"), [(400, 16, "bridges"), (400, 2, "two_edge"), (400, 2, "articulation"), (400, 2, "components"), (1, 16, "two_edge")])
def test_chosen_methods_answer_alike(spark, omega, bound, question):
    edges, vertices = random_edges(10, n=30, extra=12)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    got = solve(g, question, omega, bound=bound)
    rows = [tuple(r) for r in got.rows.select(*sorted(got.rows.columns)).collect()]
    assert sorted(rows) == sorted({"bridges": want["bridges"], "articulation": {(v,) for v in want["ap"]}, "two_edge": {(c, v) for v, c in want["two"].items()}, "components": {(c, v) for v, c in want["comp"].items()}}[question])
    wide = bound == 2 and question == "articulation"
    assert got.plan["family"] == ("dense" if omega == 1 or wide else "sparse") and ("rerouted" in got.plan) == wide


def test_oracle_names_trees_and_asked_clusters(spark, tmp_path):
    edges, vertices = random_edges(3, n=26, extra=18)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    o = BiconnectivityOracle.build(g, k=4, seed=2)
    number = {(r.a, r.b): r.block for r in o.edge_block().collect()}
    canonical = {(r.a, r.b): (r.block_a, r.block_b) for r in blocks.canonical_blocks(blocks.block_labelling(g, beta=0.5)).collect()}
    assert number.keys() == canonical.keys() and sorted(set(number.values())) == list(range(want["blocks"]))
    assert len(set(zip(number.values(), (canonical[e] for e in number), strict=True))) == want["blocks"]
    assert {r.vid: r.comp for r in o.two_edge_components().collect()} == want["two"]
    tree = {}
    for r in o.cut_block_tree().collect():
        tree.setdefault(r.vid, set()).add(r.block)
    assert {v: len(b) for v, b in tree.items()} == {v: len(want["inc"][v]) for v in want["ap"]}
    assert {(r.a, r.b) for r in o.bridge_block_tree().collect()} == want["bridges"]
    few = spark.createDataFrame(sorted(number)[::9], "a long, b long")
    assert {(r.a, r.b): r.block for r in o.edge_block(few).collect()} == {tuple(e): number[tuple(e)] for e in sorted(number)[::9]}
    asked = o.stored.select("cluster").orderBy("cluster").limit(3)
    keys = {r.cluster for r in asked.collect()}
    assert sorted(map(str, o.views(asked).collect())) == sorted(str(r) for r in o.views().collect() if r.cluster in keys)
    pairs = spark.createDataFrame([(u * 100 + v, u, v) for u in vertices[::4] for v in vertices[::3]], "qid long, u long, v long")
    answers = [{r.qid: r[1] for r in df.collect()} for df in (o.same_block(pairs, batch=True), o.same_block_step_by_step(pairs))]
    assert answers[0] == answers[1]
    o.save(f"file://{tmp_path}/b")
    again = BiconnectivityOracle.load(g, f"file://{tmp_path}/b")
    assert {(r.a, r.b): r.block for r in again.edge_block().collect()} == number


def test_implicit_structures_equal_the_batch(spark):
    edges, vertices = random_edges(11)
    g = graph_of(spark, edges, vertices)
    o = ConnectivityOracle.build(g, k=5, seed=3)
    where = {r.vid: r.center for r in o.dec.lookup().collect()}
    asked = spark.createDataFrame([(c,) for c in sorted(set(where.values()))[::3]], "center long")
    keys = {r.center for r in asked.collect()}
    assert {(r.center, r.vid) for r in decompose.members_of(o.dec, asked).collect()} == {(c, v) for v, c in where.items() if c in keys}
    near = {(r.center, r.neighbor) for r in decompose.quotient_neighbors(o.dec).collect()}
    assert {(r.center, r.neighbor) for r in decompose.quotient_neighbors(o.dec, asked).collect()} == {p for p in near if p[0] in keys}
    parent = {r.vid: (r.center, r.parent) for r in o.dec.cluster_forest().collect()}
    assert {v: c for v, (c, _) in parent.items()} == where and all((p is None) == (v == c) and (p is None or where[p] == c) for v, (c, p) in parent.items())
    pairs = spark.createDataFrame([(1, 0, 7), (2, 0, vertices[-1]), (3, 0, 10**6)], "qid long, u long, v long")
    got = {r.qid: r.connected for r in o.connected(pairs).collect()}
    assert got == {r.qid: r.connected for r in o.connected(pairs, batch=True).collect()} and got[1] is True and got[2] is False and got[3] is None
    assert o.spanning_forest().distinct().count() == len(vertices) - len(set(brute(edges, vertices)["comp"].values()))


def test_joins_against_plain_ones(spark):
    rng = np.random.default_rng(5)
    points = [(i, float(x)) for i, x in enumerate(rng.integers(-20, 20, 60))] + [(99, None)]
    ranges = [(i, float(a), float(a + w)) for i, (a, w) in enumerate(zip(rng.integers(-25, 20, 30), rng.integers(-2, 15, 30), strict=True))]
    p, r = spark.createDataFrame(points, "p long, at double"), spark.createDataFrame(ranges, "r long, low double, high double")
    want = sorted((i, k) for i, x in points if x is not None for k, a, z in ranges if a <= x <= z)
    joined = range_join(p, r, "at", "low", "high", 4.0)
    assert sorted((x.p, x.r) for x in joined.select("p", "r").collect()) == want
    assert guarded_cross(p, r).count() == len(points) * len(ranges)
    with pytest.raises(ValueError, match="pairs are more than"):
        guarded_cross(p, r, max_rows=10)
    plan, stored = lambda df: df._jdf.queryExecution().analyzed().toString(), scratch.materialize(p, "points")
    assert "broadcast" in plan(broadcast_under(stored, 1 << 20)) and "broadcast" not in plan(broadcast_under(stored, 10))


def test_edge_files_keep_what_they_cannot_read(spark, tmp_path):
    edges = spark.createDataFrame([(1, 2), (-3, 4)], "x long, y long")
    for fmt in ("csv", "json", "text", "orc", "parquet"):
        write_edges(edges, f"{tmp_path}/{fmt}", fmt)
        assert sorted(map(tuple, read_edges(spark, f"{tmp_path}/{fmt}", fmt)[0].collect())) == [(-3, 4), (1, 2)]
    (tmp_path / "odd.txt").write_text("1 2\n 3\t4 \nx 5\n6\n\n7 8 9\n99999999999999999999 1\n")
    good, bad = read_edges(spark, f"{tmp_path}/odd.txt", "text")
    assert sorted(map(tuple, good.collect())) == [(1, 2), (3, 4)] and bad.count() == 5
    with pytest.raises(ValueError, match="unknown format"):
        read_edges(spark, "nowhere", "avro")
    g = graph_of(spark, [(1, 2)], [3])
    assert register("tiny", g, components=connect.components_star(g)) == ["v_tiny_vertices", "v_tiny_edges", "v_tiny_components"]
    assert spark.sql("select count(*) from v_tiny_components where comp = 1").head()[0] == 2


def test_scratch_tables(spark):
    rows, seen = scratch.measured(spark.range(10), "ten", total=F.col("id"))
    assert seen == {"rows": 10, "total": 45} and rows.count() == 10
    empty, seen = scratch.measured(spark.range(10).filter("id > 99"), "none", total=F.col("id"))
    assert seen == {"rows": 0, "total": 0}
    scratch.discard(rows, None, spark.range(1))
    with pytest.raises(Exception, match="FAILED_READ_FILE|PATH_NOT_FOUND|does not exist"):
        rows.count()
    assert scratch.barrier(spark.range(3), "reliable").count() == 3
    with pytest.raises(ValueError, match="unknown barrier"):
        scratch.barrier(spark.range(1), "local")

    class Cluster:
        conf = type("C", (), {"get": staticmethod(lambda *a: None)})
        sparkContext = type("S", (), {"master": "yarn", "getCheckpointDir": staticmethod(lambda: None)})

    with pytest.raises(RuntimeError, match="share"):
        scratch.scratch_dir(Cluster())


def test_kept_answers_follow_the_tables(spark, tmp_path):
    built = []
    (tmp_path / "t").write_text("a")
    ask = lambda: workloads.kept(spark, ("k", f"file://{tmp_path}"), lambda: built.append(1) or len(built))
    assert ask() == ask() == 1
    (tmp_path / "t").write_text("another length")
    assert ask() == 2
