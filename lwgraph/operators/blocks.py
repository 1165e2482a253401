"""Rooted forests from Euler circuits, block labelling, and everything read off it.

The corrected rules apply throughout: a bridge is the only member of its block and has
multiplicity one; only non-tree edges between unrelated vertices join labels; the head of
a block is the tree parent of its earliest member; an edge's block is the label of the end
that lies below the other in the tree.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.graph import CostMeter, Graph
from ..plans.scratch import discard, materialize, measured, watched
from . import local
from .connect import components_lowwrite, components_star, forest_of
from .trees import global_index, leaffix, prefix_sum


def euler_circuit(tree: DataFrame, roots: DataFrame) -> DataFrame:
    """(id, src, dst, next): arcs of the forest (a, b, eid) with their successors, broken before each root's first arc; roots(vid).

    The two arcs of edge e are 2e and 2e + 1, so that an arc's reverse is known without a join."""
    two = 2 * F.col("eid")
    arcs = tree.select(F.explode(F.array(F.struct(two.alias("id"), F.col("a").alias("src"), F.col("b").alias("dst")), F.struct((two + 1).alias("id"), F.col("b").alias("src"), F.col("a").alias("dst")))).alias("arc")).select("arc.*")
    around = Window.partitionBy("src").orderBy("dst")
    ring = arcs.select("id", "src", "dst", F.lead("id").over(around).alias("then"), F.first("id").over(around).alias("first"))
    # the arc that follows (u, v) leaves v: the one after (v, u) there
    turn = ring.select(F.col("id").bitwiseXOR(F.lit(1).cast("long")).alias("id"), F.col("dst").alias("src"), F.col("src").alias("dst"), F.coalesce("then", "first").alias("next"), F.col("then").isNull().alias("wraps"))
    ends = turn.join(roots.select(F.col("vid").alias("dst"), F.lit(True).alias("is_root")), "dst", "left")
    return ends.select("id", "src", "dst", F.when(~(F.col("wraps") & F.coalesce("is_root", F.lit(False))), F.col("next")).alias("next"))


def list_rank(links: DataFrame, spread: int = 8, max_rounds: int = 64) -> DataFrame:
    """(id, left): for links (id, next, step) the sum of steps from each to the end of its list.

    A hash picks one in ``spread`` as a milestone.  All others double their way to the next
    milestone, which takes rounds like the logarithm of the widest gap; the milestones alone are
    ranked in the same way, and the last few in one task."""
    now, seen = measured(links.select("id", "next", "step"), "list-rank")
    if now.count() <= local.ROWS:
        return materialize(local.local_ranks(now), "ranks")
    stone = F.pmod(F.xxhash64("id", F.lit(spread)), F.lit(spread)) == 0
    aim = F.pmod(F.xxhash64("next", F.lit(spread)), F.lit(spread)) == 0
    walk, seen = measured(now.select("id", F.col("next").alias("at"), "step", (F.col("next").isNull() | aim).alias("ended")), "list-walk", going=(~F.col("ended")).cast("long"))
    discard(now)
    for _ in range(max_rounds):
        if seen["going"] == 0:
            break
        ahead = walk.select(F.col("id").alias("at"), F.col("at").alias("at2"), F.col("step").alias("more"), F.col("ended").alias("ended2"))
        moved = walk.filter("not ended").join(ahead, "at").select("id", F.col("at2").alias("at"), (F.col("step") + F.col("more")).alias("step"), F.col("ended2").alias("ended"))
        then, seen = measured(walk.filter("ended").unionByName(moved), "list-walk", going=(~F.col("ended")).cast("long"))
        discard(walk)
        walk = then
    else:
        raise RuntimeError("the list did not end")
    ranks = list_rank(walk.filter(stone).select("id", F.col("at").alias("next"), "step"), spread + 1, max_rounds)
    beyond = ranks.select(F.col("id").alias("at"), F.col("left").alias("rest"))
    out = materialize(walk.join(beyond, "at", "left").select("id", (F.col("step") + F.coalesce("rest", F.lit(0))).alias("left")), "ranks")
    discard(walk, ranks)
    return out


def root_forest(graph: Graph, tree: DataFrame, comp: DataFrame | None = None) -> DataFrame:
    """(vid, parent, root, first, last, idx, size, depth) rooted at each component's least vertex.

    first and last are positions in the Euler circuit (0 and 2n-1 at a root); idx is the
    preorder number over the whole forest, size that of the subtree.  Below ``local.ROWS`` one task takes the same steps."""
    if graph.vertices.count() <= local.ROWS:
        if comp is None:
            tree = materialize(tree, "tree")
            comp, _ = forest_of(tree.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb")))
            comp = graph.vertices.join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp"))
        return materialize(local.local_root_forest(tree, comp), "forest")
    tree = materialize(tree.withColumn("eid", F.monotonically_increasing_id()), "tree")
    if comp is None:
        comp, _ = forest_of(tree.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb")))
        comp = graph.vertices.join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp"))
    comp = materialize(comp, "tree-comp")
    circuit = materialize(euler_circuit(tree, comp.filter("vid = comp").select("vid")), "circuit")
    ranked = circuit.join(list_rank(circuit.select("id", "next", F.col("next").isNotNull().cast("long").alias("step"))), "id")
    sizes = comp.groupBy("comp").agg(F.count(F.lit(1)).alias("n"))
    placed = ranked.join(comp.withColumnRenamed("vid", "src"), "src").join(sizes, "comp").select(F.expr("id div 2").alias("eid"), "src", "dst", "comp", (2 * F.col("n") - 2 - F.col("left")).alias("pos"))
    # the earlier arc of an edge leads down: one group an edge
    both = placed.groupBy("eid").agg(F.min("pos").alias("first"), F.max("pos").alias("last"), F.min_by("src", "pos").alias("parent"), F.min_by("dst", "pos").alias("vid"), F.min("comp").alias("root"))
    down = both.select("vid", "parent", "root", "first", "last")
    tops = comp.filter("vid = comp").join(sizes, "comp").select("vid", F.lit(None).cast("bigint").alias("parent"), F.col("comp").alias("root"), F.lit(0).cast("bigint").alias("first"), (2 * F.col("n") - 1).alias("last"))
    rows = down.unionByName(tops)
    # ranks 1.. of down arcs leave 0 to the root; a vertex that is entered at first and left at last holds half the ranks between
    rows = rows.withColumn("size", F.expr("(last - first + 1) div 2"))
    numbered = materialize(global_index(rows, ["root", "first"], "idx"), "numbered")
    base = numbered.filter("parent is null").select("root", F.col("idx").alias("base"))
    # up to a vertex's entry there are idx - base entries among `first` arcs, the rest are exits
    depth = 2 * (F.col("idx") - F.col("base")) - F.col("first")
    out = materialize(numbered.join(base, "root").withColumn("depth", depth.cast("int")).select("vid", "parent", "root", "first", "last", "idx", "size", "depth"), "forest")
    discard(tree, comp, circuit, numbered)
    return out


def nontree_edges(graph: Graph, forest: DataFrame) -> DataFrame:
    """(a, b, extra): edges beside the tree; ``extra`` counts the copies that are not the tree's."""
    tree = forest.filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"), F.lit(1).alias("in_tree"))
    return graph.edges.join(tree, ["a", "b"], "left").filter("in_tree is null").select("a", "b", F.col("mult").alias("extra"))


def low_high(nontree: DataFrame, forest: DataFrame) -> DataFrame:
    """forest rows with low and high: least and greatest idx that the subtree's vertices and their non-tree neighbours have."""
    arcs = nontree.select(F.explode(F.array(F.struct(F.col("a").alias("vid"), F.col("b").alias("other")), F.struct(F.col("b").alias("vid"), F.col("a").alias("other")))).alias("arc")).select("arc.*")
    place = forest.select(F.col("vid").alias("other"), F.col("idx").alias("oidx"))
    reach = arcs.join(place, "other").groupBy("vid").agg(F.min("oidx").alias("lo"), F.max("oidx").alias("hi"))
    rows = forest.join(reach, "vid", "left").withColumn("w_lo", F.least("idx", "lo")).withColumn("w_hi", F.greatest("idx", "hi")).drop("lo", "hi")
    rows = materialize(rows, "reach")
    return materialize(rows.join(leaffix(rows), "vid").drop("w_lo", "w_hi"), "low-high")


@dataclass
class BlockLabelling:
    graph: Graph
    forest: DataFrame  # vid, parent, root, first, last, idx, size, depth, low, high, separating
    label: DataFrame  # vid, block (no roots)
    head: DataFrame  # block, head_vid, members


def block_labelling(graph: Graph, forest: DataFrame | None = None, meter: CostMeter | None = None, **options) -> BlockLabelling:
    """The block of the tree edge above every vertex, and the head of every block.  Below ``local.ROWS`` one task takes the same steps."""
    if forest is None:
        comp, tree = components_lowwrite(graph, want_forest=True, meter=meter, **options)
        forest = root_forest(graph, tree, comp)
        if meter:
            meter.add("rooted forest", ops=2 * forest.count(), writes=forest.count(), rounds=1)
    if _in_one_task(graph):
        return _labelled(graph, local.local_labelling(graph.edges, forest), meter)
    nontree = materialize(nontree_edges(graph, forest), "nontree")
    rows = low_high(nontree, forest)
    above = forest.select(F.col("vid").alias("parent"), F.col("idx").alias("pidx"), F.col("size").alias("psize"))
    inside = (F.col("low") >= F.col("pidx")) & (F.col("high") < F.col("pidx") + F.col("psize"))
    rows = materialize(rows.join(above, "parent", "left").withColumn("separating", F.when(F.col("parent").isNotNull(), inside)).drop("pidx", "psize"), "separating")
    x = rows.select(F.col("vid").alias("a"), F.col("idx").alias("ia"), F.col("size").alias("sa"))
    y = rows.select(F.col("vid").alias("b"), F.col("idx").alias("ib"), F.col("size").alias("sb"))
    unrelated = ~((F.col("ia") <= F.col("ib")) & (F.col("ib") < F.col("ia") + F.col("sa"))) & ~((F.col("ib") <= F.col("ia")) & (F.col("ia") < F.col("ib") + F.col("sb")))
    cross = nontree.join(x, "a").join(y, "b").filter(unrelated).select("a", "b")
    kept = rows.filter("parent is not null and not separating").select(F.col("vid").alias("a"), F.col("parent").alias("b")).unionByName(cross)
    members = rows.filter("parent is not null").select("vid")
    label = materialize(components_star(Graph(members, kept.select("a", "b"))).select("vid", F.col("comp").alias("block")), "label")
    if meter:
        meter.add("block labelling", ops=graph.edges.count(), writes=label.count(), rounds=1)
    head = label.join(rows.select("vid", "parent", "idx"), "vid").groupBy("block").agg(F.min_by("parent", "idx").alias("head_vid"), F.count(F.lit(1)).alias("members"))
    return BlockLabelling(graph, rows, label, materialize(head, "head"))


def _in_one_task(graph: Graph) -> bool:
    """Edges are two numbers each: twice as many are no more than the arcs of ``local.ROWS`` edges."""
    return graph.vertices.count() <= local.ROWS and graph.edges.count() <= 2 * local.ROWS


def _labelled(graph: Graph, rows: DataFrame, meter: CostMeter | None = None) -> BlockLabelling:
    made = materialize(rows, "labelled")
    label = made.filter("parent is not null").select("vid", "block")
    if meter:
        meter.add("block labelling", ops=graph.edges.count(), writes=label.count(), rounds=1)
    return BlockLabelling(graph, made.drop("block", "head_vid", "members"), label, made.filter("members is not null").select(F.col("vid").alias("block"), "head_vid", "members"))


SHARE = 1 << 19  # vertices of whole components to a task


def whole_labelling(graph: Graph, connected=None) -> BlockLabelling:
    """The labelling over the inner forest: of a small graph forest, circuit and labels take one task and one write.

    Of a larger one whole components are dealt to tasks; where one component is too large for a task all goes in rounds.
    ``connected`` gives ((vid, comp), forest (a, b)) of the graph, where they are made already."""
    if _in_one_task(graph):
        return _labelled(graph, local.local_whole_labelling(graph.vertices, graph.edges))
    if connected:
        comp, tree = connected()
    else:
        comp, tree = forest_of(graph.edges.select("a", "b", F.col("a").alias("ra"), F.col("b").alias("rb")))
        comp = materialize(graph.vertices.join(comp, "vid", "left").select("vid", F.coalesce("comp", "vid").alias("comp")), "whole-comp")
        tree = tree.select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    sizes = comp.groupBy("comp").agg(F.count(F.lit(1)).alias("n"))
    placed = graph.edges.select("a", "b").join(comp.withColumnRenamed("vid", "a"), "a")
    if (sizes.agg(F.max("n")).head()[0] or 0) <= local.ROWS and (placed.groupBy("comp").count().agg(F.max("count")).head()[0] or 0) <= 2 * local.ROWS:
        shares = max(graph.vertices.count() // SHARE, graph.edges.count() // (2 * SHARE)) + 1
        share = F.pmod(F.xxhash64("comp"), F.lit(shares)).cast("int").alias("share")
        bases = prefix_sum(sizes, ["comp"], "n", "base").select("comp", "base")
        return _labelled(graph, local.labelled_components(comp.join(bases, "comp").select("vid", "base", share), placed.select("a", "b", share)))
    return block_labelling(graph, root_forest(graph, tree, comp))


def bridges(bl: BlockLabelling) -> DataFrame:
    """(a, b): single-member blocks whose tree edge has no copy."""
    lone = bl.head.filter("members = 1").join(bl.label, "block").select("vid", "head_vid")
    pairs = lone.select(F.least("vid", "head_vid").alias("a"), F.greatest("vid", "head_vid").alias("b"))
    return pairs.join(bl.graph.edges.filter("mult = 1").select("a", "b"), ["a", "b"])


def articulation_points(bl: BlockLabelling) -> DataFrame:
    """(vid): heads of a block; roots need two."""
    bl.graph.refuse_expanded("articulation points")
    heads = bl.head.groupBy(F.col("head_vid").alias("vid")).agg(F.count(F.lit(1)).alias("blocks"))
    return heads.join(bl.forest.select("vid", "parent"), "vid").filter("parent is not null or blocks > 1").select("vid")


def edge_block(bl: BlockLabelling, edges: DataFrame) -> DataFrame:
    """(a, b, block) of given edges: the label of the lower end."""
    bl.graph.refuse_expanded("blocks")
    x = bl.forest.select(F.col("vid").alias("a"), F.col("idx").alias("ia"), F.col("size").alias("sa"))
    y = bl.forest.select(F.col("vid").alias("b"), F.col("idx").alias("ib"))
    low = F.when((F.col("ia") <= F.col("ib")) & (F.col("ib") < F.col("ia") + F.col("sa")), F.col("b")).otherwise(F.col("a"))
    return edges.select("a", "b").join(x, "a").join(y, "b").withColumn("vid", low).join(bl.label, "vid").select("a", "b", "block")


def canonical_blocks(bl: BlockLabelling) -> DataFrame:
    """(a, b, block_a, block_b): every edge with the least edge of its block, a name that no choice of tree changes."""
    rows = materialize(edge_block(bl, bl.graph.edges), "edge-blocks")
    names = rows.groupBy("block").agg(F.min(F.struct("a", "b")).alias("name"))
    return rows.join(names, "block").select("a", "b", F.col("name.a").alias("block_a"), F.col("name.b").alias("block_b"))


def same_block(bl: BlockLabelling, pairs: DataFrame) -> DataFrame:
    """(qid, same_block) for (qid, u, v): equal labels, or one heads the other's block; a vertex is with itself."""
    bl.graph.refuse_expanded("blocks")
    l, h = bl.label, bl.head.select("block", "head_vid")
    named = bl.graph.vertices.join(l, "vid", "left").join(h, "block", "left")
    x = named.select(F.col("vid").alias("u"), F.col("block").alias("bu"), F.col("head_vid").alias("hu"))
    y = named.select(F.col("vid").alias("v"), F.col("block").alias("bv"), F.col("head_vid").alias("hv"))
    yes = (F.col("u") == F.col("v")) | F.coalesce(F.col("bu") == F.col("bv"), F.lit(False)) | F.coalesce(F.col("hu") == F.col("v"), F.lit(False)) | F.coalesce(F.col("hv") == F.col("u"), F.lit(False))
    return pairs.join(x, "u").join(y, "v").select("qid", yes.alias("same_block"))


def is_bridge(bl: BlockLabelling, edges: DataFrame) -> DataFrame:
    yes = bridges(bl).withColumn("is_bridge", F.lit(True))
    return edges.select("qid", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).join(yes, ["a", "b"], "left").select("qid", F.coalesce("is_bridge", F.lit(False)).alias("is_bridge"))


def block_cut_tree(bl: BlockLabelling) -> DataFrame:
    """(vid, block) incidences of articulation points and blocks."""
    bl.graph.refuse_expanded("blocks")
    points = articulation_points(bl)
    pairs = bl.label.unionByName(bl.head.select(F.col("head_vid").alias("vid"), "block"))
    return pairs.join(points, "vid", "left_semi").distinct()


def two_edge_components(bl: BlockLabelling) -> DataFrame:
    """(vid, comp): components once the bridges are gone; only tree edges are looked at."""
    cut = bridges(bl)
    tree = bl.forest.filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"))
    return components_star(Graph(bl.graph.vertices, tree.join(cut, ["a", "b"], "left_anti")))


def bridge_block_tree(bl: BlockLabelling, classes: DataFrame | None = None) -> DataFrame:
    """(comp_a, comp_b, a, b): the bridges between two-edge components."""
    classes = classes if classes is not None else two_edge_components(bl)
    x, y = classes.select(F.col("vid").alias("a"), F.col("comp").alias("comp_a")), classes.select(F.col("vid").alias("b"), F.col("comp").alias("comp_b"))
    return bridges(bl).join(x, "a").join(y, "b").select("comp_a", "comp_b", "a", "b")


def edge_array_baseline(graph: Graph, forest: DataFrame | None = None, meter: CostMeter | None = None) -> DataFrame:
    """(a, b, block): the classical method, which relates edges and stores one row for each.

    Every edge is an object of its own: a tree edge goes by its lower end, another by a negative number.
    A non-tree edge is related to the tree edge above its later end, and where its ends are unrelated
    the tree edges above both ends are related; a tree edge is related to the one above it where its
    subtree reaches out of the parent's.  Components of the relation are the blocks."""
    if forest is None:
        comp, tree = components_lowwrite(graph, beta=0.5, want_forest=True, meter=meter)
        forest = root_forest(graph, tree, comp)
    nontree = nontree_edges(graph, forest)
    rows = low_high(nontree, forest)
    numbered = materialize(global_index(nontree.select("a", "b"), ["a", "b"], "n").select("a", "b", (-1 - F.col("n")).alias("object")), "edge-objects")
    place = forest.select("vid", "idx", "size")
    ends = numbered.join(place.toDF("a", "ia", "sa"), "a").join(place.toDF("b", "ib", "sb"), "b")
    later, earlier = F.when(F.col("ia") > F.col("ib"), F.col("a")).otherwise(F.col("b")), F.when(F.col("ia") > F.col("ib"), F.col("b")).otherwise(F.col("a"))
    reach = F.when(F.col("ia") < F.col("ib"), F.col("ia") + F.col("sa")).otherwise(F.col("ib") + F.col("sb"))
    ends = ends.select("object", later.alias("later"), earlier.alias("earlier"), (F.greatest("ia", "ib") >= reach).alias("unrelated"))
    above = forest.select(F.col("vid").alias("parent"), F.col("parent").alias("above"), F.col("idx").alias("pidx"), F.col("size").alias("psize"))
    out_of = (F.col("low") < F.col("pidx")) | (F.col("high") >= F.col("pidx") + F.col("psize"))
    climbs = rows.filter("parent is not null").join(above, "parent").filter(F.col("above").isNotNull() & out_of).select(F.col("vid").alias("x"), F.col("parent").alias("y"))
    related = ends.select(F.col("object").alias("x"), F.col("later").alias("y")).unionByName(ends.filter("unrelated").select(F.col("earlier").alias("x"), F.col("later").alias("y"))).unionByName(climbs)
    tree_edges = forest.filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"), F.col("vid").alias("object"))
    objects, told = measured(tree_edges.unionByName(numbered), "edge-objects")
    seen, looked = watched(related)
    pairs = materialize(seen.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "edge-relation")
    named = components_star(Graph(objects.select(F.col("object").alias("vid")), pairs), meter)
    out, kept = measured(objects.join(named.toDF("object", "block"), "object").select("a", "b", "block"), "edge-array")
    if meter:
        meter.add("edge array", ops=looked.rows + graph.edges.count(), writes=told["rows"] + kept["rows"], rounds=1)
    return out
