"""Query structures that store one row a cluster: connectivity, and biconnectivity through cluster views."""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.graph import CostMeter, Graph
from ..plans.scratch import discard, materialize, measured
from . import local
from .blocks import BlockLabelling, bridges, whole_labelling
from .connect import forest_of
from .decompose import CenterDecomposition, cover_orphans, decompose, lookup_center, met_of, next_hops, quotient
from .trees import lca, prefix_sum, rootfix, width


def _quotient_graph(q: DataFrame, where: DataFrame) -> Graph:
    return Graph(where.select(F.col("center").alias("vid")).distinct(), q.select(F.col("ca").alias("a"), F.col("cb").alias("b"), "mult"))


@dataclass
class ConnectivityOracle:
    """Kept: centers with a bit, one component label a center, and the forest of the quotient; building writes tables of all vertices besides."""

    dec: CenterDecomposition
    labels: DataFrame  # center, comp
    forest: DataFrame | None = None  # a, b: one original edge for each tree edge of the quotient

    @classmethod
    def build(cls, graph: Graph, omega: float = 16.0, *, k: int | None = None, seed: int = 0, quotient_mode: str = "implicit", meter: CostMeter | None = None, dec: CenterDecomposition | None = None) -> ConnectivityOracle:
        """``dec``: a decomposition of the graph that is there already."""
        k = k or max(2, round(omega**0.5))
        dec = dec or decompose(graph, k, seed, meter=meter)
        where = dec.lookup(meter)
        q = quotient(dec.graph, where)
        if quotient_mode == "explicit":
            q, seen = measured(q, "quotient")
            if meter:
                meter.add("quotient", ops=2 * dec.graph.edges.count(), writes=seen["rows"])
        elif meter:
            meter.add("quotient", ops=2 * dec.graph.edges.count())
        comp, trees = forest_of(q.select(F.col("ca").alias("a"), F.col("cb").alias("b"), F.col("rep_a").alias("ra"), F.col("rep_b").alias("rb")), meter)
        forest, kept = measured(trees.select(F.col("ra").alias("a"), F.col("rb").alias("b")), "quotient-forest")
        labels = where.select("center").distinct().join(comp.withColumnRenamed("vid", "center"), "center", "left").select("center", F.coalesce("comp", "center").alias("comp"))
        labels, seen = measured(labels, "oracle-labels")
        if meter:
            meter.add("labels", writes=seen["rows"], rounds=1)
            meter.add("quotient forest", writes=kept["rows"])
        return cls(dec, labels, forest)

    def component(self, asked: DataFrame | None = None, meter: CostMeter | None = None) -> DataFrame:
        """(vid, comp): the center's label; labels are center names, equal within a component.

        Asked vertices are looked up by their own searches, which write nothing that is kept; without them all are, in one batch."""
        where = self.dec.lookup() if asked is None else lookup_center(self.dec, asked, meter=meter)
        return where.join(self.labels, "center").select("vid", "comp")

    def connected(self, pairs: DataFrame, *, batch: bool = False, meter: CostMeter | None = None) -> DataFrame:
        """(qid, connected); unknown vertices give null.  ``batch`` looks all vertices up at once, for pairs in the order of n."""
        asked = None if batch else pairs.select(F.explode(F.array("u", "v")).alias("vid")).distinct().join(self.dec.graph.vertices, "vid", "left_semi")
        c = materialize(self.component(asked, meter), "asked-components")
        x, y = c.select(F.col("vid").alias("u"), F.col("comp").alias("cu")), c.select(F.col("vid").alias("v"), F.col("comp").alias("cv"))
        return pairs.join(x, "u", "left").join(y, "v", "left").select("qid", (F.col("cu") == F.col("cv")).alias("connected"))

    def spanning_forest(self) -> DataFrame:
        """(a, b): the clusters' own trees and one original edge for each tree edge of the quotient."""
        inner = self.dec.cluster_forest().filter("parent is not null").select(F.least("vid", "parent").alias("a"), F.greatest("vid", "parent").alias("b"))
        return inner.unionByName(self.forest)

    def save(self, path: str) -> None:
        """Centers, labels, the quotient's forest and a manifest."""
        self.dec.centers.write.parquet(f"{path}/centers")
        self.labels.write.parquet(f"{path}/labels")
        self.forest.write.parquet(f"{path}/forest")
        _save_manifest(self.labels.sparkSession, path, self.dec)

    @classmethod
    def load(cls, graph: Graph, path: str) -> ConnectivityOracle:
        spark = graph.vertices.sparkSession
        return cls(_load_decomposition(graph, path), spark.read.parquet(f"{path}/labels"), spark.read.parquet(f"{path}/forest"))


def _save_manifest(spark, path: str, dec: CenterDecomposition) -> None:
    spark.createDataFrame([(json.dumps({"k": dec.k, "order": dec.order}),)], "value string").coalesce(1).write.text(f"{path}/manifest")


def _load_decomposition(graph: Graph, path: str) -> CenterDecomposition:
    """From the stored centers; the tables of the batch look-up are made anew."""
    spark = graph.vertices.sparkSession
    told = json.loads(spark.read.text(f"{path}/manifest").head()[0])
    centers = spark.read.parquet(f"{path}/centers")
    primaries = centers.filter("is_primary").select("vid")
    hops = next_hops(graph, primaries, order=told["order"])
    _, implicit = cover_orphans(graph, primaries, hops, told["k"])
    return CenterDecomposition(graph, told["k"], centers, hops, materialize(implicit, "implicit"), told["order"])


# --- local block labelling of one small graph -------------------------------------------------------


def lowpoint_blocks(edges: list[tuple]) -> tuple[dict, set]:
    """(block of every edge, bridges) of a small multigraph by one iterative depth-first search; copies of an edge are listed again."""
    near: dict = {}
    for n, (a, b) in enumerate(edges):
        near.setdefault(a, []).append((b, n))
        near.setdefault(b, []).append((a, n))
    order, low, block, cut, count = {}, {}, {}, set(), 0
    for top in near:
        if top in order:
            continue
        order[top] = low[top] = len(order)
        stack, held = [(top, None, iter(near[top]))], []
        while stack:
            v, via, rest = stack[-1]
            for w, n in rest:
                if n == via:
                    continue
                if w not in order:
                    order[w] = low[w] = len(order)
                    held.append(n)
                    stack.append((w, n, iter(near[w])))
                    break
                if order[w] < order[v]:
                    held.append(n)
                    low[v] = min(low[v], order[w])
            else:
                stack.pop()
                if stack:
                    u = stack[-1][0]
                    low[u] = min(low[u], low[v])
                    if low[v] >= order[u]:
                        part = []
                        while True:
                            n = held.pop()
                            part.append(n)
                            if n == via:
                                break
                        for n in part:
                            block[n] = count
                        if len(part) == 1:
                            cut.add(part[0])
                        count += 1
    return block, cut


FACT_SCHEMA = "cluster long, kind string, x long, y long, block int, open boolean, edge_open boolean, blocks int, ea long, eb long, kid long"


VIEW_CLUSTERS = 1 << 15  # clusters to a block of views


def _facts(table: pa.Table) -> pa.Table:
    """Facts of the clusters of one block from their view rows (cluster, x, y, origin, ea, eb, kid).

    kind ``point``: x is a member or a port (ports are negative: -1 - cluster), y the least point of its local two-edge
    class, with open bits; ``member``: a local block that x lies in; ``edge``: the local block of an edge of the view,
    with the original edge (ea, eb) and the child cluster that a tree edge leads to; ``count``: the blocks that the
    cluster owns, x its root, block the local block towards the parent.  All views of the block are labelled at once, as
    one graph rooted at each view's least points; local blocks are numbered by the least point that their trees enter,
    whatever order the rows come in."""
    cluster, x, origin = (table.column(c).to_numpy() for c in ("cluster", "x", "origin"))
    y = table.column("y").fill_null(0).to_numpy()
    real = np.flatnonzero(origin >= 0)
    # points: (cluster, x) in order
    ends = np.concatenate([cluster, cluster[real]]), np.concatenate([x, y[real]])
    order = np.lexsort(ends[::-1])
    c, v = ends[0][order], ends[1][order]
    fresh = np.concatenate([[True], (c[1:] != c[:-1]) | (v[1:] != v[:-1])])[: len(c)]
    at = np.empty(len(c), np.int64)
    at[order] = np.cumsum(fresh) - 1
    c, v, n = c[fresh], v[fresh], int(fresh.sum())
    clusters, first = np.unique(c, return_index=True)
    own, k = np.searchsorted(clusters, c), len(clusters)
    # a root mark is at the parent's port, or at the root cluster's least member
    marks, root = np.flatnonzero(origin == -1), np.full(k, -1)
    root[own[at[marks]]] = at[marks]
    port = (root >= 0) & (v[np.maximum(root, 0)] < 0)
    # different edges, with the copies of each
    p, q = np.minimum(at[real], at[len(x) :]), np.maximum(at[real], at[len(x) :])
    pairs, place, copies = np.unique(p * n + q, return_inverse=True, return_counts=True)
    a, b = (pairs // n, pairs % n) if n else (p, q)
    top, chosen = local.forest_arrays(a, b, n)
    made = local.rooted_arrays(a[chosen], b[chosen], top)
    idx, size = made["idx"], made["size"]
    told = local.labelled_arrays(a, b, made["parent"], idx, size)
    lower = np.where((idx[a] <= idx[b]) & (idx[b] < idx[a] + size[a]), b, a)
    block = told["block"][lower]
    cut = chosen & (copies == 1) & (told["members"][block] == 1)
    two, _ = local.forest_arrays(a[~cut], b[~cut], n)  # two-edge classes: components without the bridges
    names = np.unique(block)
    before = np.searchsorted(names, first)  # blocks of earlier clusters
    number = lambda of: np.searchsorted(names, of) - before[own[of]]
    owned = np.bincount(own[names], minlength=k)
    # incidences of points and blocks: below a block's edge, or its head
    inside = np.flatnonzero(told["block"] >= 0)
    who, which = np.concatenate([inside, told["head"][names]]), np.concatenate([told["block"][inside], names])
    order = np.lexsort((which, who))
    who, which = who[order], which[order]
    up = np.full(k, -1)  # the block towards the parent
    ported = np.flatnonzero(port[own[who]] & (who == root[own[who]]))[::-1]
    up[own[who[ported]]] = which[ported]
    opens = np.zeros(n, bool)
    met = which == up[own[who]]
    opens[who[met]] = True
    edge_opens = port[own] & (two == two[np.maximum(root[own], 0)])
    of = block[place]
    parts = [n, len(who), len(real), k]

    def column(kind, *values):
        """One array a kind of row, null where there is none; a pair has its own mask of nulls."""
        made = []
        for size_, value in zip(parts, values, strict=True):
            if value is None:
                made.append(pa.nulls(size_, kind))
            else:
                value, none = value if isinstance(value, tuple) else (value, None)
                made.append(value.combine_chunks().cast(kind) if isinstance(value, pa.ChunkedArray) else pa.array(value, kind, mask=none))
        return pa.chunked_array(made, kind)

    kept = table.take(pa.array(real))
    above = number(np.maximum(up, 0)) if n else up
    return pa.table({
        "cluster": column(pa.int64(), c, c[who], cluster[real], clusters),
        "kind": column(pa.string(), *(np.full(s, w, object) for s, w in zip(parts, ("point", "member", "edge", "count"), strict=True))),
        "x": column(pa.int64(), v, v[who], x[real], np.where(root >= 0, v[np.maximum(root, 0)], clusters)),
        "y": column(pa.int64(), v[two], None, y[real], None),
        "block": column(pa.int32(), None, number(which), number(of), (above, up < 0)),
        "open": column(pa.bool_(), opens, met, of == up[own[lower[place]]], None),
        "edge_open": column(pa.bool_(), edge_opens, None, cut[place], None),
        "blocks": column(pa.int32(), None, None, None, owned - port),
        "ea": column(pa.int64(), None, None, kept.column("ea"), None),
        "eb": column(pa.int64(), None, None, kept.column("eb"), None),
        "kid": column(pa.int64(), None, None, kept.column("kid"), None)})


@dataclass
class BiconnectivityOracle:
    """Stored, one row a cluster: parent, tree edge, ranks, quotient block, bridge bit, open bits, blocking depths."""

    dec: CenterDecomposition
    labelling: BlockLabelling | None  # of the quotient, while building
    stored: DataFrame  # cluster, parent, anchor, port_at, depth, idx, size, root, qblock, q_bridge, open, edge_open, block_depth, bridge_depth
    quotient_edges: DataFrame | None  # a plan
    numbers: DataFrame | None = None  # cluster, offset, top_block, tree_block, owned: made when block numbers are first asked for
    facts: DataFrame | None = None  # of all clusters: written while building, read by questions about all of them, never saved

    @classmethod
    def build(cls, graph: Graph, omega: float = 16.0, *, k: int | None = None, seed: int = 0, meter: CostMeter | None = None, dec: CenterDecomposition | None = None) -> BiconnectivityOracle:
        """``dec``: a decomposition of the graph that is there already."""
        graph.refuse_expanded("blocks")
        k = k or max(2, round(omega**0.5))
        dec = dec or decompose(graph, k, seed, meter=meter)
        where = dec.lookup(meter)
        q, seen = measured(quotient(dec.graph, where), "quotient-once")
        if meter:
            meter.add("quotient", ops=2 * dec.graph.edges.count(), writes=seen["rows"])
        qg = _quotient_graph(q, where)
        qg.vertices = materialize(qg.vertices, "quotient-vertices")
        bl = whole_labelling(qg)
        cut = bridges(bl).select(F.col("a").alias("ca"), F.col("b").alias("cb"), F.lit(True).alias("q_bridge"))
        rep = q.select("ca", "cb", "rep_a", "rep_b").join(cut, ["ca", "cb"], "left")
        owner = where.select(F.col("vid").alias("rep_a"), F.col("center").alias("own_a"))
        f = bl.forest.select(F.col("vid").alias("cluster"), "parent", "root", "idx", "size", "depth")
        pairs = f.withColumn("ca", F.least("cluster", "parent")).withColumn("cb", F.greatest("cluster", "parent")).join(rep, ["ca", "cb"], "left").join(owner, "rep_a", "left")
        mine = F.col("own_a") == F.col("cluster")
        rows = pairs.select("cluster", "parent", "root", "idx", "size", "depth", F.when(mine, F.col("rep_a")).otherwise(F.col("rep_b")).alias("anchor"), F.when(mine, F.col("rep_b")).otherwise(F.col("rep_a")).alias("port_at"), F.coalesce("q_bridge", F.lit(False)).alias("q_bridge"))
        rows = materialize(rows.join(bl.label.select(F.col("vid").alias("cluster"), F.col("block").alias("qblock")), "cluster", "left"), "clusters")
        made = cls(dec, bl, rows, q)
        facts = made.local_facts()
        bits = facts.filter("kind = 'point' and x < 0").select((-1 - F.col("x")).alias("cluster"), F.col("cluster").alias("parent"), "open", "edge_open")
        rows = rows.join(bits, ["cluster", "parent"], "left")
        depths = rows.select(F.col("cluster").alias("vid"), "parent", F.when(F.col("parent").isNotNull() & ~F.coalesce("open", F.lit(False)), F.col("depth")).otherwise(0).alias("blocked"),
                             F.when(F.col("parent").isNotNull() & ~F.coalesce("edge_open", F.lit(False)), F.col("depth")).otherwise(0).alias("cut"))
        b1 = rootfix(depths.select("vid", "parent", "blocked"), "blocked", "block_depth").withColumnRenamed("vid", "cluster")
        b2 = rootfix(depths.select("vid", "parent", "cut"), "cut", "bridge_depth").withColumnRenamed("vid", "cluster")
        made.stored = materialize(rows.join(b1, "cluster").join(b2, "cluster"), "bicon-stored")
        if meter:
            meter.add("stored rows", writes=made.stored.count(), rounds=1)
        return made

    def _placed(self, clusters: DataFrame | None) -> tuple[DataFrame, DataFrame]:
        """((vid, cluster) of the members, edges (a, b, mult, xa, xb) that touch them).

        Of asked clusters only: members by searches outward from the centers, far ends by the look-ups that these took."""
        edges = self.dec.graph.edges
        if clusters is None:
            members = self.dec.lookup().select("vid", F.col("center").alias("cluster"))
            named = members
        else:
            met = met_of(self.dec, clusters.select(F.col("cluster").alias("center")))
            members, named = met.filter("own = center").select("vid", F.col("center").alias("cluster")), met.select("vid", F.col("own").alias("cluster")).distinct()
            near = members.select("vid")
            edges = edges.join(near.toDF("a"), "a", "left_semi").unionByName(edges.join(near.toDF("b"), "b", "left_semi")).distinct()
        x, y = named.toDF("a", "xa"), named.toDF("b", "xb")
        return members, edges.join(x, "a").join(y, "b")

    def views(self, clusters: DataFrame | None = None) -> DataFrame:
        """Cluster views: inner edges; tree edges to ports; chains of ports in one block; outer edges re-pointed to ports; a root mark.

        Nothing of it is kept; copies of an edge appear as often as they exist."""
        from pyspark.sql import Window

        want = None if clusters is None else materialize(clusters.select("cluster").distinct(), "asked-clusters")
        where, placed = self._placed(want)
        placed = materialize(placed, "placed")
        only = lambda df, c="cluster": df if want is None else df.join(want.toDF(c), c, "left_semi")
        none, times = F.lit(None).cast("bigint"), F.explode(F.expr("sequence(1, mult)"))
        row = lambda df, x, y, origin, ea=none, eb=none, kid=none: df.select("cluster", x.alias("x"), y.alias("y"), origin.alias("origin"), ea.alias("ea"), eb.alias("eb"), kid.alias("kid"))
        c = F.col
        inner = row(placed.filter("xa = xb").withColumn("cluster", c("xa")), c("a"), c("b"), times, c("a"), c("b"))
        t = self.stored.filter("parent is not null").select("cluster", "parent", "anchor", "port_at", "idx", "size", "qblock")
        lo, hi = F.least("anchor", "port_at"), F.greatest("anchor", "port_at")
        kids = only(t.withColumnRenamed("cluster", "kid").withColumnRenamed("parent", "cluster"))
        down = row(kids, c("port_at"), -1 - c("kid"), F.lit(1), lo, hi, c("kid"))
        mine = only(t)
        up = row(mine, c("anchor"), -1 - c("parent"), F.lit(1), lo, hi)
        # ports of one quotient block: children by their own block, the parent's port by the cluster's
        ports = kids.select("cluster", (-1 - c("kid")).alias("port"), "qblock").unionByName(mine.select("cluster", (-1 - c("parent")).alias("port"), "qblock"))
        link = row(ports.withColumn("y", F.lead("port").over(Window.partitionBy("cluster", "qblock").orderBy("port"))).filter("y is not null"), c("port"), c("y"), F.lit(1))
        # an outer edge that is not the tree's representative ends at the port whose subtree holds the far cluster
        sides = F.array(F.struct(c("xa").alias("cluster"), c("a").alias("x"), c("xb").alias("other"), c("b").alias("far")), F.struct(c("xb").alias("cluster"), c("b").alias("x"), c("xa").alias("other"), c("a").alias("far")))
        far = only(placed.filter("xa <> xb").select(F.explode(sides).alias("o"), "mult", "a", "b").select("o.*", "mult", "a", "b"))
        reps = mine.select("cluster", c("anchor").alias("x"), c("port_at").alias("far"), F.lit(1).alias("is_rep")).unionByName(kids.select("cluster", c("port_at").alias("x"), c("anchor").alias("far"), F.lit(1).alias("is_rep")))
        far = far.join(reps, ["cluster", "x", "far"], "left").withColumn("mult", c("mult") - F.coalesce("is_rep", F.lit(0))).filter("mult > 0")
        spots = self.stored.select(c("cluster").alias("other"), c("idx").alias("oidx"))
        me = only(self.stored.select("cluster", c("idx").alias("cidx"), c("size").alias("csize"), c("parent").alias("cparent")))
        located = far.join(spots, "other").join(me, "cluster")
        below = (c("oidx") > c("cidx")) & (c("oidx") < c("cidx") + c("csize"))
        above = row(located.filter(~below), c("x"), -1 - c("cparent"), times, c("a"), c("b"))
        # the child whose range holds oidx is the one with the greatest idx not above it: one sorted pass a cluster
        marks = kids.select("cluster", c("idx").alias("oidx"), "kid", none.alias("x"), F.lit(0).alias("mult"), none.alias("a"), none.alias("b"))
        probes = located.filter(below).select("cluster", "oidx", none.alias("kid"), "x", "mult", "a", "b")
        run = marks.unionByName(probes).withColumn("child", F.last("kid", ignorenulls=True).over(Window.partitionBy("cluster").orderBy("oidx", "mult").rowsBetween(Window.unboundedPreceding, 0)))
        deeper = row(run.filter("x is not null"), c("x"), -1 - c("child"), times, c("a"), c("b"))
        tops = row(only(self.stored.select("cluster", F.when(c("parent").isNotNull(), -1 - c("parent")).alias("port"))).join(where.groupBy("cluster").agg(F.min("vid").alias("least")), "cluster"), F.coalesce("port", "least"), none, F.lit(-1))
        out = inner
        for more in (down, up, link, above, deeper, tops, row(where, c("vid"), none, F.lit(-2))):
            out = out.unionByName(more)
        return out

    def local_facts(self, clusters: DataFrame | None = None) -> DataFrame:
        """Local blocks and bits of the given clusters: O(k) rows each, some thousands of clusters to a block.  Those of all are written once."""
        if clusters is None and self.facts is not None:
            return self.facts
        blocks = max(min(width(self.stored), self.stored.count()), (self.stored if clusters is None else clusters).count() // VIEW_CLUSTERS + 1)
        block = F.pmod(F.xxhash64("cluster"), F.lit(blocks)).cast("int")
        found = self.views(clusters).groupBy(block.alias("view_block")).applyInArrow(_facts, FACT_SCHEMA)
        if clusters is None:
            self.facts = found = materialize(found, "facts")
        return found

    # --- queries ------------------------------------------------------------------------------

    def is_bridge(self, edges: DataFrame | None = None) -> DataFrame:
        """(a, b, is_bridge) of all or the given edges (a, b): inside a cluster its own view tells, a tree edge has its stored bit, other outer edges never are.

        Given edges are looked up one by one, and only the clusters that hold one are opened."""
        e = self.dec.graph.edges
        if edges is None:
            where, opened = self.dec.lookup(), None
        else:
            e = materialize(e.join(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), ["a", "b"], "left_semi"), "asked-edges")
            where = materialize(lookup_center(self.dec, e.select(F.explode(F.array("a", "b")).alias("vid")).distinct()), "asked-ends")
        where = where.select("vid", F.col("center").alias("cluster"))
        placed = e.join(where.toDF("a", "xa"), "a").join(where.toDF("b", "xb"), "b")
        if edges is not None:
            opened = placed.filter("xa = xb").select(F.col("xa").alias("cluster"))
        cuts = self.local_facts(opened).filter("kind = 'edge' and x >= 0 and y >= 0 and edge_open").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), F.lit(True).alias("inner_cut"))
        t = self.stored.filter("parent is not null and q_bridge").select(F.least("anchor", "port_at").alias("a"), F.greatest("anchor", "port_at").alias("b"), F.lit(True).alias("tree_cut"))
        return placed.join(cuts.distinct(), ["a", "b"], "left").join(t, ["a", "b"], "left").select(
            "a", "b", (F.when(F.col("xa") == F.col("xb"), F.coalesce("inner_cut", F.lit(False))).otherwise(F.coalesce("tree_cut", F.lit(False))) & (F.col("mult") == 1)).alias("is_bridge"))

    def is_articulation(self, asked: DataFrame | None = None, *, facts: DataFrame | None = None) -> DataFrame:
        """(vid): of all or the asked vertices those that lie in two local blocks of their cluster's view; ``facts`` are those of all clusters, where at hand."""
        opened = None if asked is None else lookup_center(self.dec, asked.select("vid")).select(F.col("center").alias("cluster"))
        found = (self.local_facts(opened) if facts is None else facts).filter("kind = 'member' and x >= 0").groupBy(F.col("x").alias("vid")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("vid")
        return found if asked is None else found.join(asked.select("vid"), "vid", "left_semi")

    # --- names of blocks and two-edge classes ---------------------------------------------------

    def number_blocks(self, facts: DataFrame | None = None) -> DataFrame:
        """(cluster, offset, top_block, tree_block): where a cluster's own blocks begin, its local block towards the parent, and the number of that block.

        The block of a cluster's tree edge is found in the parent's view; where it goes on to the parent's own
        parent it has the parent's number: a chain, flattened by doubling.  One row a cluster is kept."""
        if self.numbers is None:
            facts = self.local_facts() if facts is None else facts
            counts = facts.filter("kind = 'count'").select("cluster", F.col("blocks").cast("bigint").alias("owned"), F.col("block").alias("top_block"))
            offsets = materialize(prefix_sum(counts, ["cluster"], "owned", "offset").select("cluster", "offset", "top_block", "owned"), "block-offsets")
            seen = facts.filter("kind = 'edge' and kid is not null").select(F.col("cluster").alias("parent"), F.col("kid").alias("cluster"), "block", "open")
            held = seen.join(offsets.select(F.col("cluster").alias("parent"), F.col("offset").alias("base"), F.col("top_block").alias("above")), "parent")
            chain = held.select("cluster", F.when(F.col("open"), F.col("parent")).alias("up"), F.when(~F.col("open"), _own_number("base", "block", "above")).alias("number"))
            self.numbers = materialize(offsets.join(_down_the_chain(chain, "number").withColumnRenamed("number", "tree_block"), "cluster", "left"), "block-numbers")
            discard(offsets)
        return self.numbers

    def edge_block(self, edges: DataFrame | None = None, *, facts: DataFrame | None = None) -> DataFrame:
        """(a, b, block): the number of the block of all or the given edges, from the view of one end's cluster.

        The cluster owns the block, or it is the one that its tree edge lies in.  ``facts`` are those of all clusters, where at hand."""
        facts = self.local_facts() if edges is None and facts is None else facts
        numbers, asked, opened = self.number_blocks(facts), None, None
        if edges is not None:
            asked = materialize(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "asked-edges")
            opened = lookup_center(self.dec, asked.select(F.col("a").alias("vid"))).select(F.col("center").alias("cluster"))
        facts = (self.local_facts(opened) if facts is None else facts).filter("kind = 'edge' and ea is not null").select("cluster", F.col("ea").alias("a"), F.col("eb").alias("b"), F.col("block").alias("local"), "open")
        found = facts.join(numbers, "cluster").select("a", "b", F.when(F.col("open"), F.col("tree_block")).otherwise(_own_number("offset", "local", "top_block")).alias("block"))
        found = found.groupBy("a", "b").agg(F.min("block").alias("block"))
        return found if asked is None else found.join(asked, ["a", "b"], "left_semi")

    def cut_block_tree(self, facts: DataFrame | None = None) -> DataFrame:
        """(vid, block): every articulation point with the numbers of its blocks; ``facts`` are those of all clusters, where at hand."""
        facts = self.local_facts() if facts is None else facts
        numbers = self.number_blocks(facts)
        inside = facts.filter("kind = 'member' and x >= 0").join(self.is_articulation(facts=facts).withColumnRenamed("vid", "x"), "x", "left_semi")
        return inside.join(numbers.select("cluster", "offset", "top_block", "tree_block"), "cluster").select(F.col("x").alias("vid"), F.when(F.col("open"), F.col("tree_block")).otherwise(_own_number("offset", "block", "top_block")).alias("block"))

    def two_edge_components(self) -> DataFrame:
        """(vid, comp): two-edge classes named by their least vertex.

        A local class that holds the parent's port goes on in the parent's view as the class of this cluster's port there."""
        points = self.local_facts().filter("kind = 'point'").select("cluster", "x", F.col("y").alias("leader"), "edge_open")
        own = lambda: F.struct(F.col("cluster").alias("at"), "leader")
        ports = points.filter("x < 0").select((-1 - F.col("x")).alias("kid"), "cluster", "leader", "edge_open").join(self.stored.select(F.col("cluster").alias("kid"), F.col("parent").alias("cluster")), ["kid", "cluster"])
        chain = ports.select(F.col("kid").alias("cluster"), F.when(F.col("edge_open"), F.col("cluster")).alias("up"), F.when(~F.col("edge_open"), own()).alias("name"))
        above = _down_the_chain(chain, "name").withColumnRenamed("name", "above")
        named = points.filter("x >= 0").join(above, "cluster", "left").select(F.col("x").alias("vid"), F.when(F.col("edge_open"), F.col("above")).otherwise(own()).alias("name"))
        least = named.groupBy("name").agg(F.min("vid").alias("comp"))
        return named.join(least, "name").select("vid", "comp")

    def bridge_block_tree(self) -> DataFrame:
        """(comp_a, comp_b, a, b): the bridges between two-edge classes."""
        classes = materialize(self.two_edge_components(), "two-edge")
        cut = self.is_bridge().filter("is_bridge").select("a", "b")
        return cut.join(classes.toDF("a", "ca"), "a").join(classes.toDF("b", "cb"), "b").select(F.least("ca", "cb").alias("comp_a"), F.greatest("ca", "cb").alias("comp_b"), "a", "b")

    # --- keeping ----------------------------------------------------------------------------------

    def save(self, path: str) -> None:
        """Centers, the stored rows, the numbers of blocks and a manifest."""
        self.dec.centers.write.parquet(f"{path}/centers")
        self.stored.write.parquet(f"{path}/stored")
        self.number_blocks().write.parquet(f"{path}/numbers")
        _save_manifest(self.stored.sparkSession, path, self.dec)

    @classmethod
    def load(cls, graph: Graph, path: str) -> BiconnectivityOracle:
        spark = graph.vertices.sparkSession
        return cls(_load_decomposition(graph, path), None, spark.read.parquet(f"{path}/stored"), None, spark.read.parquet(f"{path}/numbers"))

    def _pair_points(self, pairs: DataFrame, batch: bool) -> DataFrame:
        known = self.dec.graph.vertices
        if batch:
            where = self.dec.lookup()
        else:
            where = lookup_center(self.dec, pairs.select(F.explode(F.array("u", "v")).alias("vid")).distinct().join(known, "vid", "left_semi"))
        where = materialize(where.select("vid", F.col("center").alias("cluster")), "pair-centers")
        out = pairs.join(where.toDF("u", "cu"), "u").join(where.toDF("v", "cv"), "v")
        spans = self.stored.select(F.col("cluster").alias("vid"), "parent", "root", "idx", "size", "depth")
        met = lca(spans, out.select("qid", F.col("cu").alias("u"), F.col("cv").alias("v")))
        return materialize(out.join(met.withColumnRenamed("lca", "t"), "qid"), "pair-points")

    def _opened(self, pairs: DataFrame, batch: bool) -> tuple[DataFrame, DataFrame]:
        """(pairs with their clusters and meeting places, facts of these clusters).

        ``batch`` opens every cluster once, for pairs in the order of n; else only those of the pairs and of their meeting places."""
        p = self._pair_points(pairs, batch)
        opened = None if batch else p.select(F.explode(F.array("cu", "cv", "t")).alias("cluster")).filter("cluster is not null")
        return p, self.local_facts() if batch else materialize(self.local_facts(opened), "pair-facts")

    def _pairs(self, p: DataFrame, facts: DataFrame, *, edge: bool) -> DataFrame:
        """Shared walk: each end must be open up to the port below the common cluster; there the two points must agree."""
        bit, deep = ("edge_open", "bridge_depth") if edge else ("open", "block_depth")
        points = facts.filter("kind = 'point'").select("cluster", "x", bit, F.col("y").alias("edge_class"))
        depth = self.stored.select("cluster", "depth", "parent", "idx", F.col(deep).alias("deep"))
        both_ends = F.explode(F.array(*[F.struct(F.lit(end).alias("end"), F.col(end).alias("vid"), F.col(f"c{end}").alias("cluster")) for end in ("u", "v")]))
        ends = p.select("qid", "t", both_ends.alias("e")).select("qid", "t", "e.*")
        own = ends.join(points.select("cluster", F.col("x").alias("vid"), F.col(bit).alias("self_open")), ["cluster", "vid"], "left").join(depth, "cluster")
        # the port below t on the way is t's last child, in preorder, that does not come after the cluster; a cluster has O(k) children
        low = own.filter("cluster <> t").select("t", "idx", "qid", "end", "self_open", "deep")
        kids = self.stored.filter("parent is not null").select(F.col("parent").alias("t"), F.struct("idx", F.col("cluster").alias("kid"), F.col("depth").alias("kdepth")).alias("k")).join(low.select("t").distinct(), "t", "left_semi")
        lists = kids.groupBy("t").agg(F.collect_list("k").alias("kids"))
        before = F.array_max(F.filter("kids", lambda x: x["idx"] <= F.col("idx")))
        below = low.join(lists, "t").withColumn("k", before).select("qid", "end", "self_open", "deep", "k.kid", "k.kdepth")
        # every cluster strictly below t's child on the way up must have an open port: the deepest blocked one is not below the child
        walked = below.select("qid", "end", (-1 - F.col("kid")).alias("point"), (F.col("self_open") & (F.col("deep") <= F.col("kdepth"))).alias("ok"))
        stay = own.filter("cluster = t").select("qid", "end", F.col("vid").alias("point"), F.lit(True).alias("ok"))
        at = materialize(walked.unionByName(stay), "pair-ends")
        u, v = at.filter("end = 'u'").select("qid", F.col("point").alias("pu"), F.col("ok").alias("ou")), at.filter("end = 'v'").select("qid", F.col("point").alias("pv"), F.col("ok").alias("ov"))
        both = p.select("qid", F.col("t").alias("cluster")).join(u, "qid").join(v, "qid")
        if edge:
            cls = facts.filter("kind = 'point'").select("cluster", "x", F.col("y").alias("c"))
            agree = both.join(cls.toDF("cluster", "pu", "c1"), ["cluster", "pu"], "left").join(cls.toDF("cluster", "pv", "c2"), ["cluster", "pv"], "left").withColumn("meet", (F.col("pu") == F.col("pv")) | F.coalesce(F.col("c1") == F.col("c2"), F.lit(False)))
        else:
            inc = facts.filter("kind = 'member'").groupBy("cluster", "x").agg(F.collect_set("block").alias("bs"))
            agree = both.join(inc.toDF("cluster", "pu", "b1"), ["cluster", "pu"], "left").join(inc.toDF("cluster", "pv", "b2"), ["cluster", "pv"], "left").withColumn("meet", (F.col("pu") == F.col("pv")) | F.coalesce(F.arrays_overlap("b1", "b2"), F.lit(False)))
        yes = agree.select("qid", (F.col("ou") & F.col("ov") & F.col("meet")).alias("yes"))
        return p.select("qid").join(yes, "qid", "left").select("qid", F.coalesce("yes", F.lit(False)).alias("yes"))

    def same_block(self, pairs: DataFrame, *, batch: bool = False) -> DataFrame:
        """(qid, same_block) of pairs (qid, u, v): at most three clusters are opened a pair."""
        return self._pairs(*self._opened(pairs, batch), edge=False).withColumnRenamed("yes", "same_block")

    def same_edge_block(self, pairs: DataFrame, *, batch: bool = False) -> DataFrame:
        """(qid, same_edge_block): no bridge separates the pair."""
        return self._pairs(*self._opened(pairs, batch), edge=True).withColumnRenamed("yes", "same_edge_block")

    def same_blocks(self, pairs: DataFrame, *, batch: bool = False) -> DataFrame:
        """(qid, same_block, same_edge_block): both answers from clusters that are opened once."""
        opened = self._opened(pairs, batch)
        return self._pairs(*opened, edge=False).withColumnRenamed("yes", "same_block").join(self._pairs(*opened, edge=True).withColumnRenamed("yes", "same_edge_block"), "qid")

    def same_block_step_by_step(self, pairs: DataFrame) -> DataFrame:
        """(qid, same_block) by the other split of cases: one cluster an ancestor of the other or not, and the walk taken cluster by cluster.

        Uses no blocking depths and no numbering of the quotient: a cross-check of ``same_block``.  Tasks hold all clusters and a
        share of the pairs, or whole trees of clusters and the pairs inside; where one tree is above ``local.ROWS`` the walk goes in rounds."""
        facts = self.local_facts()
        where = self.dec.lookup().select("vid", F.col("center").alias("cluster"))
        up = materialize(self.stored.select("cluster", "parent", "depth", "root"), "step-parents")
        opens = facts.filter("kind = 'point'").select("cluster", F.col("x").alias("point"), F.coalesce("open", F.lit(False)).alias("open"))
        at = pairs.join(where.toDF("u", "cu"), "u").join(where.toDF("v", "cv"), "v").select("qid", F.col("u").alias("pu"), "cu", F.col("v").alias("pv"), "cv", F.lit(True).alias("ok"))
        small = trees = max(up.count(), opens.count()) <= local.ROWS
        if not small:
            largest = opens.select("cluster").join(up.select("cluster", "root"), "cluster").groupBy("root").count().agg(F.max("count")).head()[0] or 0
            trees = largest <= local.ROWS
        ended = materialize((local.local_climbs if small else local.tree_climbs)(materialize(at, "step"), up, opens), "step") if trees else None
        near = up.select("cluster", "parent", "depth")
        du, dv = near.toDF("cu", "fu", "du"), near.toDF("cv", "fv", "dv")
        while not trees:
            at, seen = measured(at.join(du, "cu").join(dv, "cv").join(opens.toDF("cu", "pu", "open_u"), ["cu", "pu"], "left").join(opens.toDF("cv", "pv", "open_v"), ["cv", "pv"], "left"), "step", going=(F.col("cu") != F.col("cv")).cast("long"))
            done = at.filter("cu = cv").select("qid", F.col("cu").alias("cluster"), "pu", "pv", "ok")
            ended = done if ended is None else ended.unionByName(done)
            if seen["going"] == 0:
                break
            # the deeper end climbs; where neither is an ancestor of the other both climb in the end; at a root there is no way on
            climbs_u, climbs_v = F.col("du") >= F.col("dv"), F.col("dv") > F.col("du")
            stuck = (climbs_u & F.col("fu").isNull()) | (climbs_v & F.col("fv").isNull())
            going = at.filter("cu <> cv").filter(~stuck)
            at = going.select("qid", F.when(climbs_u, -1 - F.col("cu")).otherwise(F.col("pu")).alias("pu"), F.when(climbs_u, F.col("fu")).otherwise(F.col("cu")).alias("cu"),
                              F.when(climbs_v, -1 - F.col("cv")).otherwise(F.col("pv")).alias("pv"), F.when(climbs_v, F.col("fv")).otherwise(F.col("cv")).alias("cv"),
                              (F.col("ok") & F.when(climbs_u, F.coalesce("open_u", F.lit(False))).otherwise(F.coalesce("open_v", F.lit(False)))).alias("ok"))
        inc = facts.filter("kind = 'member'").groupBy("cluster", "x").agg(F.collect_set("block").alias("bs"))
        agree = ended.join(inc.toDF("cluster", "pu", "b1"), ["cluster", "pu"], "left").join(inc.toDF("cluster", "pv", "b2"), ["cluster", "pv"], "left")
        yes = agree.select("qid", (F.col("ok") & ((F.col("pu") == F.col("pv")) | F.coalesce(F.arrays_overlap("b1", "b2"), F.lit(False)))).alias("yes"))
        known = pairs.join(where.toDF("u", "cu"), "u", "left_semi").join(where.toDF("v", "cv"), "v", "left_semi")
        return known.select("qid").join(yes, "qid", "left").select("qid", F.coalesce("yes", F.lit(False)).alias("same_block"))

    def block_count(self) -> DataFrame:
        """(blocks): owned local blocks of all clusters add up to the blocks of the graph; prefix sums of them number the blocks."""
        return self.number_blocks().agg(F.coalesce(F.max(F.col("offset") + F.col("owned")), F.lit(0)).cast("bigint").alias("blocks"))


def _own_number(offset: str, local: str, top: str):
    """The number of a block that a cluster owns: its local blocks in order, the one towards the parent left out."""
    return F.col(offset) + F.col(local) - F.coalesce((F.col(local) > F.col(top)).cast("bigint"), F.lit(0))


def _down_the_chain(chain: DataFrame, value: str, max_rounds: int = 64) -> DataFrame:
    """(cluster, value) where a row without a value takes that of the row it points ``up`` to, by doubling."""
    if chain.count() <= local.ROWS:
        tops = local.local_tops(chain.select(F.col("cluster").alias("id"), "up", F.lit(0).cast("long").alias("value"))).select(F.col("id").alias("cluster"), "top")
        return tops.join(chain.select(F.col("cluster").alias("top"), value), "top").select("cluster", value)
    now, seen = measured(chain.select("cluster", "up", value), "chain", open=F.col("up").isNotNull().cast("long"))
    for _ in range(max_rounds):
        if seen["open"] == 0:
            return now.select("cluster", value)
        ahead = now.select(F.col("cluster").alias("up"), F.col("up").alias("up2"), F.col(value).alias("more"))
        moved = now.join(ahead, "up", "left").select("cluster", F.when(F.col("up").isNotNull(), F.col("up2")).alias("up"), F.coalesce(value, "more").alias(value))
        now, seen = measured(moved, "chain", open=F.col("up").isNotNull().cast("long"))
    raise RuntimeError("the chain did not end")
