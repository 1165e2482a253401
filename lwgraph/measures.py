"""Costs and measures of the methods over the paper's sweeps, re-expressed on the given tables.

Figures that follow from the graph alone have SQL beside them; the others depend on hashes and
rounds, and the claims about them are queries that count violations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .extras import mesh, mesh_decomposition, mesh_oracle, slice_oracle
from .operators import balls, blocks, connect, decompose, degree, local, searches
from .operators.oracles import BiconnectivityOracle, ConnectivityOracle
from .operators.trees import global_index
from .plans.graph import CostMeter, Graph, choose_method, predicted
from .plans.scratch import materialize
from .plans.solve import solve
from .sources import oracle
from .sources.views import edge_sql, graph_view, hash_below, hash_text, hash_threshold, load
from .workloads import RANGE, _one, grouped_components, grouped_sql, kept

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
OMEGAS = (1, 4, 16, 64, 256, 1024)
NONE = "select cast(0 as bigint) as violations"


def query(sql: str | None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


def violations(spark: SparkSession, *broken: bool) -> DataFrame:
    return spark.createDataFrame([(sum(map(int, broken)),)], "violations long")


# --- construction costs ---------------------------------------------------------------------------

BUILDERS = {
    "breadth-first": lambda g, meter: connect.bfs_components(g, meter),
    "label propagation": lambda g, meter: connect.label_propagation(g, meter),
    "recursive contraction": lambda g, meter: connect.recursive_contraction(g, 0.4, meter=meter),
    "stored messages": lambda g, meter: balls.ball_partition(g, 0.4, materialize_messages=True, meter=meter),
    "low-write, beta 1/2": lambda g, meter: connect.components_lowwrite(g, beta=0.5, meter=meter),
    "low-write, beta 1/4": lambda g, meter: connect.components_lowwrite(g, beta=0.25, meter=meter),
    "oracle, k 8": lambda g, meter: ConnectivityOracle.build(g, k=8, seed=1, meter=meter).labels,
}


def built(spark: SparkSession, d: str, view: str) -> dict[str, CostMeter]:
    """The meters of every construction on one view."""

    def run():
        g, out = graph_view(spark, d, view).fixed(), {}
        bounded = g.max_degree() <= 16  # the decomposition is for bounded degrees: a star has no balanced split
        for name, build in BUILDERS.items():
            if name.startswith("oracle") and not bounded:
                continue
            out[name] = CostMeter(name)
            build(g, out[name]).count()
        return out

    return kept(spark, ("w1", d, view), run)


def costs(spark: SparkSession, meters: dict[str, CostMeter]) -> DataFrame:
    """method, ops, writes, rounds, scratch_peak, and work at every write cost."""
    rows = [(name, *m.total(), m.peak()) for name, m in meters.items()]
    made = spark.createDataFrame(rows, "method string, ops long, writes long, rounds long, scratch_peak long")
    return made.withColumn("omega", F.explode(F.array(*[F.lit(w) for w in OMEGAS]))).withColumn("work", F.col("ops") + F.col("omega") * F.col("writes"))


@query(None)
def w1_costs_dense(spark, d):
    """Every construction on the dense view: operations, stored rows, rounds, and work over the write costs."""
    return costs(spark, built(spark, d, "part_supplier"))


@query(None)
def w1_costs_sparse(spark, d):
    return costs(spark, built(spark, d, "event_mesh"))


@query(NONE)
def w1_claims(spark, d):
    """On the dense view the low-write method stores fewer rows than recursive contraction and than stored messages do,
    fewer than there are edges, and its work wins at high write costs."""
    g, m = graph_view(spark, d, "part_supplier"), built(spark, d, "part_supplier")
    edges = g.edges.count()
    low, contraction, messages = (m[k].total()[1] for k in ("low-write, beta 1/4", "recursive contraction", "stored messages"))
    work = lambda k: m[k].total()[0] + 1024 * m[k].total()[1]
    return violations(spark, low >= contraction, low >= messages, low >= edges, work("low-write, beta 1/4") >= work("recursive contraction"))


@query(None)
def w1_crossover(spark, d):
    """Which family the chooser takes, and which one the closed forms favour, over densities and write costs."""
    rows = []
    for view in ("part_supplier", "order_part", "order_chain", "event_mesh"):
        g = graph_view(spark, d, view)
        n, m = g.vertices.count(), g.edges.count()
        for w in OMEGAS:
            cost = {name: work for name, _, _, work in predicted(n, m, w)}
            rows.append((view, n, m, w, choose_method(n, m, w)["family"], "dense" if cost["connectivity, low-write"] <= cost["connectivity oracle"] else "sparse"))
    return spark.createDataFrame(rows, "view string, n long, m long, omega int, chosen string, cheaper string")


BLOCK_ROWS = """select n - comps as labels, blocks as heads, m as edge_array from
  (select count(distinct (block_a, block_b)) as blocks, count(*) as m from ({b})), (select count(*) as n, count(distinct comp) as comps from ({c}))"""


@query(BLOCK_ROWS.format(b=oracle.blocks("part_supplier_slice"), c=oracle.components("part_supplier_slice")))
def w2_rows_kept(spark, d):
    """Rows that the block labelling keeps, one a vertex and one a block, beside the classical array's one an edge."""
    g = graph_view(spark, d, "part_supplier_slice").fixed()
    comp, tree = connect.components_lowwrite(g, beta=0.5, want_forest=True)
    forest = blocks.root_forest(g, tree, comp)
    bl = blocks.block_labelling(g, forest)
    return spark.createDataFrame([(bl.label.count(), bl.head.count(), blocks.edge_array_baseline(g, forest).count())], "labels long, heads long, edge_array long")


@query(None)
def w2_costs(spark, d):
    """Block labelling, classical array and oracle on a sparse view: operations, stored rows, rounds."""
    g = graph_view(spark, d, "order_fragments").fixed()
    meters = {name: CostMeter(name) for name in ("block labelling", "edge array", "oracle, k 4")}
    blocks.block_labelling(g, meter=meters["block labelling"], beta=0.5)
    blocks.edge_array_baseline(g, meter=meters["edge array"])
    BiconnectivityOracle.build(g, k=4, seed=1, meter=meters["oracle, k 4"])
    return costs(spark, meters)


# --- the decomposition ----------------------------------------------------------------------------


@query(None)
def w3_query_costs(spark, d):
    """Vertices that a look-up visits, over k: mean, tail and largest, beside k and k ln n."""
    out, g = None, mesh(spark, d)
    n = g.vertices.count()
    for k in (4, 8, 16):
        told = decompose.lookup_center(mesh_decomposition(spark, d, k=k), g.vertices, costs=True)
        one = told.agg(F.avg("visited").alias("mean"), F.percentile_approx("visited", 0.99, 10_000).alias("p99"), F.max("visited").alias("most")).select(F.lit(k).alias("k"), "mean", "p99", "most", (F.lit(float(k)) * F.log(F.lit(float(n)))).alias("k_ln_n"))
        out = one if out is None else out.unionByName(one)
    return out


@query(NONE)
def w3_claims(spark, d):
    """Clusters stay within k, their number times k over n stays flat, look-ups visit at most some k ln n vertices."""
    from .extras import w3_k_sweep

    sweep, visits = {r["k"]: r for r in w3_k_sweep(spark, d).collect()}, {r["k"]: r for r in w3_query_costs(spark, d).collect()}
    flat = [r["clusters_k_over_n"] for r in sweep.values()]
    return violations(spark, any(r["largest"] > k for k, r in sweep.items()), max(flat) > 3 * min(flat), any(r["p99"] > 8 * r["k_ln_n"] for r in visits.values()))


@query(None)
def w4_query_batches(spark, d):
    """A batch of a thousand vertices and one of a thousand hub-biased ones: vertices visited by a component query."""
    o, g = mesh_oracle(spark, d), graph_view(spark, d, "event_mesh")
    order = F.md5(F.concat(F.lit("batch:"), F.col("vid").cast("string")))
    uniform = g.vertices.orderBy(order).limit(1000).withColumn("batch", F.lit("uniform"))
    hubs = g.arcs().groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("degree")).orderBy(F.desc("degree"), order).limit(1000).select("vid").withColumn("batch", F.lit("hubs"))
    asked = materialize(uniform.unionByName(hubs), "batches")
    told = decompose.lookup_center(o.dec, asked, costs=True)
    return asked.join(told, "vid").join(o.labels, "center").groupBy("batch").agg(F.count(F.lit(1)).alias("queries"), F.avg("visited").alias("mean"), F.max("visited").alias("most"), F.countDistinct("comp").alias("components"))


# --- balls ------------------------------------------------------------------------------------------

SWEEP = ((0.5, "shifted", "min_id"), (0.25, "shifted", "min_id"), (0.125, "shifted", "min_id"), (0.5, "literal", "min_id"), (0.25, "literal", "min_id"), (0.5, "shifted", "fraction"))


def swept(spark: SparkSession, d: str) -> DataFrame:
    def run():
        g, out = graph_view(spark, d, "event_mesh").fixed(), None
        for beta, start, tie in SWEEP:
            one = balls.ball_stats(g, balls.ball_partition(g, beta, 1, start_rule=start, tie_rule=tie, parents=False), beta).select(F.lit(beta).alias("beta"), F.lit(start).alias("start_rule"), F.lit(tie).alias("tie_rule"), "*")
            out = one if out is None else out.unionByName(one)
        return materialize(out, "beta-sweep")

    return kept(spark, ("w5", d), run)


@query(None)
def w5_beta_sweep(spark, d):
    """Cut edges over beta m and radius times beta over ln n, for start rules and tie rules."""
    return swept(spark, d)


@query(NONE)
def w5_claims(spark, d):
    """With late starts the cut share falls with beta and stays below 1.5 beta; radii stay within 2 ln n / beta."""
    rows = swept(spark, d).collect()
    late = sorted(((r["beta"], r["cut_edges"]) for r in rows if r["start_rule"] == "shifted" and r["tie_rule"] == "min_id"), reverse=True)
    return violations(spark, any(x[1] <= y[1] for x, y in zip(late, late[1:], strict=False)), any(r["cut_over_beta"] > 1.5 or r["radius_ratio"] > 2 for r in rows if r["start_rule"] == "shifted"))


# --- many graphs over one base ----------------------------------------------------------------------

SHARES, SEEDS = (0.2, 0.4, 0.6, 0.8, 1.0), (1, 2, 3, 4, 5)
KEPT = [(p, s) for p in SHARES for s in SEEDS]


def percolated(spark: SparkSession, d: str, base: Graph | None = None) -> Graph:
    """The union of all samples: sample i's vertices lie in a range of their own; no sample is stored."""
    g, vertices, edges = base or graph_view(spark, d, "event_mesh"), None, None
    for i, (p, s) in enumerate(KEPT):
        v = g.vertices.select((F.col("vid") + i * RANGE).alias("vid"))
        e = g.edges.filter(hash_below(p, F.lit(s), F.col("a"), F.col("b"))).select((F.col("a") + i * RANGE).alias("a"), (F.col("b") + i * RANGE).alias("b"), "mult")
        vertices, edges = (v, e) if vertices is None else (vertices.unionByName(v), edges.unionByName(e))
    return Graph(vertices, edges)


def sampled_places(base: Graph) -> tuple[DataFrame, int]:
    """((a, b, mult, held), number of vertices): edges between places of the vertices in order, with bit i for those that sample i of ``percolated`` holds."""
    spots = materialize(global_index(base.vertices, ["vid"], "spot").select("vid", "spot"), "spots")
    hashes = base.edges.select("a", "b", "mult", *[hash_text(F.lit(s), F.col("a"), F.col("b")).alias(f"h{s}") for s in SEEDS])
    bit = lambda i, p, s: F.when(F.col(f"h{s}") < hash_threshold(p), F.lit(1 << i)).otherwise(0) if p < 1 else F.lit(1 << i)
    held = sum((bit(i, p, s).cast("long") for i, (p, s) in enumerate(KEPT)), F.lit(0).cast("long"))
    x, y = spots.toDF("a", "pa"), spots.toDF("b", "pb")
    return hashes.select("a", "b", "mult", held.alias("held")).join(x, "a").join(y, "b").select(F.col("pa").alias("a"), F.col("pb").alias("b"), "mult", "held"), spots.count()


_SAMPLES = ", ".join(f"({i}, {p}, {s}, '{hash_threshold(p) if p < 1 else 'g'}')" for i, (p, s) in enumerate(KEPT))
_PERC = f"""with recursive samples(i, p, seed, t) as (values {_SAMPLES}), base as materialized (select distinct least(x, y) as a, greatest(x, y) as b from ({edge_sql('event_mesh')}) where y is not null),
e as materialized (select i, a, b from base, samples where substr(md5(concat_ws(':', cast(seed as varchar), cast(a as varchar), cast(b as varchar))), 1, 8) < t),
s as materialized (select i, a as u, b as v from e union all select i, b, a from e),
comp(i, vid, c) using key (i, vid) as (
  select i, event_id, event_id from events, samples
  union
  select s.i, s.v, min(comp.c) from comp join s on s.i = comp.i and s.u = comp.vid join recurring.comp r on r.i = s.i and r.vid = s.v where comp.c < r.c group by s.i, s.v)
select cast(p as double) as p, cast(seed as integer) as seed, count(*) as components, cast(max(n) as bigint) as largest from (select i, c, count(*) as n from comp group by i, c) join samples using (i) group by p, seed"""


@query(_PERC)
def w6_percolation_sweep(spark, d):
    """Components and the largest one of every hash-sampled mesh, five shares by five seeds."""
    sizes = connect.component_sizes(connect.components_star(percolated(spark, d)))
    found = sizes.groupBy(F.floor(F.col("comp") / RANGE).cast("int").alias("i")).agg(F.count(F.lit(1)).alias("components"), F.max("size").alias("largest"))
    names = spark.createDataFrame([(i, p, s) for i, (p, s) in enumerate(KEPT)], "i int, p double, seed int")
    return found.join(F.broadcast(names), "i").select("p", "seed", "components", "largest")


@query(None)
def w6_percolation_bridges(spark, d):
    """Bridges of every sample: whole samples are dealt to tasks, above ``local.ROWS`` edges as places in arrays, or where one is too large for a task from one labelling of their union."""
    sample = F.floor(F.col("a") / RANGE).cast("int")
    base = graph_view(spark, d, "event_mesh").fixed()
    if base.edges.count() <= local.ROWS:
        cut = local.local_bridges(percolated(spark, d, base).edges, sample).select(F.col("key").alias("i"))
    elif searches.is_held(base):
        cut = local.sampled_bridges(*sampled_places(base), len(KEPT), 8 * len(KEPT)).select(F.col("key").alias("i"))
    else:
        cut = blocks.bridges(blocks.block_labelling(percolated(spark, d, base).fixed(), beta=0.5)).select(sample.alias("i"))
    names = spark.createDataFrame([(i, p, s) for i, (p, s) in enumerate(KEPT)], "i int, p double, seed int")
    return names.join(cut.groupBy("i").agg(F.count(F.lit(1)).alias("bridges")), "i", "left").select("p", "seed", F.coalesce("bridges", F.lit(0)).alias("bridges"))


# --- edges by time, weight and relationship ---------------------------------------------------------


_MONTH = f"""select p.m as key, e.x, e.y from ({edge_sql('order_chain')}) e join (select o_orderkey, year(o_orderdate) * 12 + month(o_orderdate) as m from orders) p on p.o_orderkey = e.x
join (select o_orderkey, year(o_orderdate) * 12 + month(o_orderdate) as m from orders) q on q.o_orderkey = e.y and q.m = p.m where e.x <> e.y"""


@query(grouped_sql(_MONTH))
def q_month_comps(spark, d):
    """Components of the order chain inside every month of order dates, all months at once."""
    o = load(spark, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("bigint").alias("key"))
    e = graph_view(spark, d, "order_chain").edges
    both = e.join(o.toDF("a", "key"), "a").join(o.toDF("b", "key"), ["b", "key"])
    return grouped_components(both.select("key", F.col("a").alias("x"), F.col("b").alias("y")))


_FLAG = "select (ascii(l_returnflag) - 65) * 2 + cast(l_quantity >= 25 as integer) as key, 1000000000 + l_partkey as x, l_suppkey as y from lineitem where l_quantity >= 49 or l_quantity <= 1"


@query(grouped_sql(_FLAG))
def w8_flag_quantity_components(spark, d):
    """Components of part and supplier pairs by return flag and kind of quantity: predicate-defined graphs over one base."""
    rows = load(spark, d, "lineitem", "l_partkey", "l_suppkey", "l_returnflag", "l_quantity").filter("l_quantity >= 49 or l_quantity <= 1")
    key = (F.ascii("l_returnflag") - 65) * 2 + (F.col("l_quantity") >= 25).cast("int")
    return grouped_components(rows.select(key.cast("bigint").alias("key"), (F.col("l_partkey") + 1_000_000_000).alias("x"), F.col("l_suppkey").alias("y")))


@query(f"""select cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, count(*) as edges from ({edge_sql('order_chain')}) e join orders on o_orderkey = least(x, y) where y is not null and x <> y group by all""".replace("(year(o", "(year(o"))
def w8_month_edges(spark, d):
    """Edges by the month of their smaller order, copies counted."""
    o = load(spark, d, "orders", "o_orderkey", "o_orderdate").select(F.col("o_orderkey").alias("a"), F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"))
    return graph_view(spark, d, "order_chain").edges.join(o, "a").groupBy("y", "m").agg(F.sum("mult").alias("edges"))


# --- ablations and choice -----------------------------------------------------------------------------


@query(None)
def w9_ablations(spark, d):
    """Centers and largest cluster of every way to split, by id and by hash order; rows written with the quotient stored and not."""
    rows, g = [], mesh(spark, d)
    for mode, order in (("recursive", "vid"), ("recursive", "hash"), ("recursive_children", "vid"), ("levelwise", "vid"), ("primary_only", "vid")):
        meter = CostMeter(mode)
        dec = decompose.decompose(g, 8, 1, mode=mode, order=order, meter=meter)
        sizes = dec.lookup().groupBy("center").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n"), F.count(F.lit(1))).head()
        rows.append((f"split {mode}, order {order}", sizes[1], sizes[0], meter.total()[1]))
    for mode in ("implicit", "explicit"):
        meter = CostMeter(mode)
        o = ConnectivityOracle.build(g, k=8, seed=1, quotient_mode=mode, meter=meter)
        rows.append((f"quotient {mode}", o.labels.count(), 8, meter.total()[1]))
    return spark.createDataFrame(rows, "variant string, clusters long, largest long, writes long")


@query(NONE)
def w9_claims(spark, d):
    """Splits keep clusters within k whatever the mode and order, plain nearest primaries do not; an implicit quotient writes less."""
    rows = {r["variant"]: r for r in w9_ablations(spark, d).collect()}
    split = [r for v, r in rows.items() if v.startswith("split") and "primary_only" not in v]
    return violations(spark, any(r["largest"] > 8 for r in split), rows["split primary_only, order vid"]["largest"] <= 8, rows["quotient implicit"]["writes"] >= rows["quotient explicit"]["writes"])


@query(oracle.components("geo_tree"))
def p1_solve_components_wide(spark, d):
    """The chooser sends hubs through degree expansion to the sparse method."""
    return solve(graph_view(spark, d, "geo_tree").fixed(), "components", 16).rows


@query(oracle.bridges("order_part"))
def p1_solve_bridges_wide(spark, d):
    """Bridges through degree expansion, positions searched and nothing of them stored."""
    return solve(graph_view(spark, d, "order_part").fixed(), "bridges", 256).rows


@query(oracle.articulation("part_supplier_slice"))
def p1_solve_articulation(spark, d):
    """Blocks do not outlive degree expansion: the question goes to the dense method."""
    return solve(graph_view(spark, d, "part_supplier_slice").fixed(), "articulation", 256, bound=4).rows


@query(oracle.components("order_part"))
def u2_positions_stored(spark, d):
    """Components of a view with hubs, edge positions kept as rows."""
    g, names = degree.expand(graph_view(spark, d, "order_part").fixed(), 8, positions="stored")
    return degree.project_components(connect.components_star(g.fixed()), materialize(names, "names"))


@query(oracle.two_edge("part_supplier_slice"))
def u3_two_edge_classes(spark, d):
    """Two-edge classes through the expanded graph, the trees' own edges never counted as bridges."""
    return degree.two_edge_classes(graph_view(spark, d, "part_supplier_slice").fixed(), 4)


# --- answers of the oracles, named canonically ----------------------------------------------------------


@query(oracle.components("event_mesh"))
def c4_oracle_canonical(spark, d):
    """The oracle's components named by their least vertex."""
    c = mesh_oracle(spark, d).component()
    return c.join(c.groupBy("comp").agg(F.min("vid").alias("least")), "comp").select("vid", F.col("least").alias("comp"))


@query(oracle.components("event_mesh"))
def c4f_quotient_forest(spark, d):
    """Cluster trees and the quotient's forest together span the graph: their components are the graph's."""
    o = mesh_oracle(spark, d)
    tree = materialize(o.spanning_forest(), "spanning")
    return connect.components_star(Graph(o.dec.graph.vertices, tree))


@query(f"select * from (with answers as ({oracle.components('event_mesh')}) select count(*) - count(distinct comp) as edges, count(distinct comp) as trees from answers)")
def c4f_forest_size(spark, d):
    o = mesh_oracle(spark, d)
    edges = o.spanning_forest().distinct().count()
    return spark.createDataFrame([(edges, o.dec.graph.vertices.count() - edges)], "edges long, trees long")


@query(oracle.components("event_mesh"))
def d5_cluster_forest(spark, d):
    """Contracting every cluster along its tree, then joining clusters by the quotient, gives the components."""
    dec = mesh_decomposition(spark, d)
    tree = dec.cluster_forest().filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"))
    q = decompose.quotient(dec.graph, dec.lookup()).select(F.col("rep_a").alias("a"), F.col("rep_b").alias("b"))
    return connect.components_star(Graph(dec.graph.vertices, tree.unionByName(q)))


@query(NONE)
def d6_members(spark, d):
    """Members by outward search from all centers are those of the batch look-up."""
    dec = mesh_decomposition(spark, d)
    want = decompose.members_of_all(dec)
    found = decompose.members_of(dec, want.select("center").distinct())
    return found.exceptAll(want).unionByName(want.exceptAll(found)).agg(F.count(F.lit(1)).alias("violations"))


@query(oracle.blocks("order_chain"))
def o13_edge_blocks(spark, d):
    """Block numbers of all edges, named by the least edge of each block."""
    rows = materialize(slice_oracle(spark, d).edge_block(), "edge-numbers")
    names = rows.groupBy("block").agg(F.min(F.struct("a", "b")).alias("name"))
    return rows.join(names, "block").select("a", "b", F.col("name.a").alias("block_a"), F.col("name.b").alias("block_b"))


_CUTS = f"""select * from (with answers as materialized ({oracle.blocks('order_chain')}), inc as materialized (select a as vid, block_a, block_b from answers union select b, block_a, block_b from answers)
select vid, block_a, block_b from inc where vid in (select vid from inc group by vid having count(*) > 1))"""


@query(_CUTS)
def o14_cut_block_tree(spark, d):
    """Articulation points with their blocks, blocks named by their least edge."""
    o = slice_oracle(spark, d)
    names = o.edge_block().groupBy("block").agg(F.min(F.struct("a", "b")).alias("name"))
    return o.cut_block_tree().join(names, "block").select("vid", F.col("name.a").alias("block_a"), F.col("name.b").alias("block_b"))


@query(_CUTS)
def t11_block_cut_tree(spark, d):
    """The same tree from the block labelling."""
    from .workloads import PROFILED, profile

    n = PROFILED.index("order_chain") * RANGE
    bl = profile(spark, d, "order_chain")["labelling"]
    inside = lambda df: df.filter((F.col("vid") >= n) & (F.col("vid") < n + RANGE))
    rows = inside(blocks.block_cut_tree(bl))
    names = materialize(blocks.edge_block(bl, bl.graph.edges), "edge-blocks").groupBy("block").agg(F.min(F.struct("a", "b")).alias("name"))
    return rows.join(names, "block").select((F.col("vid") - n).alias("vid"), (F.col("name.a") - n).alias("block_a"), (F.col("name.b") - n).alias("block_b"))


@query(NONE)
def o16_other_case_split(spark, d):
    """Pair answers by the step-by-step walk with the other split of cases equal those by blocking depths."""
    from .workloads import all_pairs

    o, pairs = slice_oracle(spark, d), all_pairs(spark, d)
    slow = o.same_block_step_by_step(pairs).withColumnRenamed("same_block", "want")
    return o.same_block(pairs, batch=True).join(slow, "qid", "full").filter("not (same_block <=> want)").agg(F.count(F.lit(1)).alias("violations"))


@query("select cast(0 as bigint) as violations")
def s4_saved_oracles(spark, d):
    """Both oracles, stored and loaded again, answer alike."""
    from .plans.scratch import new_scratch_path

    g = graph_view(spark, d, "order_fragments").fixed()
    dec = decompose.decompose(g, 4, 1)
    c, b = ConnectivityOracle.build(g, k=4, dec=dec), BiconnectivityOracle.build(g, k=4, dec=dec)
    at = new_scratch_path(spark, "saved")
    c.save(f"{at}/c")
    b.save(f"{at}/b")
    c2, b2 = ConnectivityOracle.load(g, f"{at}/c"), BiconnectivityOracle.load(g, f"{at}/b")

    def diff(x: DataFrame, y: DataFrame) -> int:
        """Rows that one has more often than the other, from one reading of both."""
        both = x.withColumn("times", F.lit(1)).unionByName(y.withColumn("times", F.lit(-1)))
        return both.groupBy(*x.columns).agg(F.sum("times").alias("times")).agg(F.coalesce(F.sum(F.abs("times")), F.lit(0))).head()[0]

    return spark.createDataFrame([(diff(c.component(), c2.component()) + diff(b.edge_block(), b2.edge_block()) + diff(b.is_bridge(), b2.is_bridge()),)], "violations long")


@query(_one(oracle.components("embedding_nn"), "select vid, comp from answers"))
def v_embedding_nn_components(spark, d):
    """Components of the graph of nearest vectors."""
    return connect.components_lowwrite(graph_view(spark, d, "embedding_nn").fixed(), beta=0.5)


@query(oracle.bridges("embedding_nn"))
def v_embedding_nn_bridges(spark, d):
    return blocks.bridges(blocks.block_labelling(graph_view(spark, d, "embedding_nn").fixed(), beta=0.5))
