"""Center decomposition: sampled primaries, nearest by lexicographically least shortest paths, split to bounded clusters.

Only the centers and their one-bit label are kept.  The map from vertices to centers
is a rule: follow ``next`` (the least neighbour one hop nearer a primary) until a center.
``lookup_center`` applies it to asked vertices from their own searches.  Building, and the batch
``lookup``, write tables of one row a vertex while they run; the meter counts these rows too.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.adjacency import adjacency
from ..plans.graph import CostMeter, Graph
from ..plans.scratch import discard, materialize, measured, watched
from ..sources.views import hash_below
from . import local, searches
from .balls import ball_partition
from .bfs import levels
from .connect import components_star
from .trees import width


def sample_primaries(graph: Graph, k: int, seed: int = 0, *, max_ratio: float = 2.0, max_tries: int = 5) -> DataFrame:
    """(vid): each vertex with probability 1/k, by hash; a sample far above expectation is drawn anew, a few times at most."""
    n = graph.vertices.count()
    for t in range(max_tries):
        found = graph.vertices.filter(hash_below(1.0 / k, F.lit(seed + t), F.col("vid")))
        if found.count() <= max_ratio * n / k + 10:
            return found
    raise RuntimeError(f"{max_tries} samples were larger than {max_ratio} times the expected size")


def _counted(table: DataFrame, stage: str, meter: CostMeter | None, rounds: int = 0) -> DataFrame:
    if meter:
        meter.add(stage, writes=table.count(), rounds=rounds)
    return table


def next_hops(graph: Graph, primaries: DataFrame, meter: CostMeter | None = None, order: str = "vid") -> DataFrame:
    """(vid, primary, hop, next) of every vertex that some primary reaches."""
    found = levels(graph, primaries, meter=meter, order=order)
    return _counted(materialize(found.select("vid", F.col("source").alias("primary"), "hop", F.col("parent").alias("next")), "next-hops"), "next hops", meter)


def _hops_of_orphans(graph: Graph, hops: DataFrame, more: DataFrame, meter: CostMeter | None, order: str) -> DataFrame:
    """Next hops in the components that had no primary; the others keep theirs."""
    lost = materialize(graph.vertices.join(hops.select("vid"), "vid", "left_anti"), "orphans")
    inside = materialize(graph.edges.join(lost.withColumnRenamed("vid", "a"), "a", "left_semi"), "orphan-edges")
    return next_hops(Graph(lost, inside), more, meter, order)


def cover_orphans(graph: Graph, primaries: DataFrame, hops: DataFrame, k: int, meter: CostMeter | None = None) -> tuple[DataFrame, DataFrame]:
    """(more primaries, implicit (vid, center)): components without a primary get their least vertex,
    as a stored primary from k vertices on, else implicitly."""
    lost = _counted(materialize(graph.vertices.join(hops.select("vid"), "vid", "left_anti"), "orphans"), "orphans", meter)
    if lost.isEmpty():
        return primaries.limit(0), lost.select("vid", F.col("vid").alias("center"))
    inside = graph.edges.join(lost.withColumnRenamed("vid", "a"), "a", "left_semi")
    comp = _counted(materialize(components_star(Graph(lost, inside)), "orphan-components"), "orphans", meter)
    sizes = comp.groupBy("comp").agg(F.count(F.lit(1)).alias("n"))
    big = sizes.filter(F.col("n") >= k).select(F.col("comp").alias("vid"))
    small = comp.join(sizes.filter(F.col("n") < k), "comp").select("vid", F.col("comp").alias("center"))
    return big, small


LOOK_ROWS = 200_000


def _trees_of(hops: DataFrame, bound: int | None = None) -> int | None:
    """The number of blocks that the trees of next hops are dealt to, whole trees; None where one tree is too large for a task."""
    if "primary" not in hops.columns:
        return None
    rows, largest = hops.groupBy("primary").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n"), F.max("n")).head()
    return None if (largest or 0) > (bound or local.ROWS) else (rows or 0) // LOOK_ROWS + 1


def _by_tree(hops: DataFrame, blocks: int):
    return hops.withColumn("tree_block", F.pmod(F.xxhash64("primary"), F.lit(blocks)).cast("int")).groupBy("tree_block")


def _first_centers(table: pa.Table) -> pa.Table:
    """(vid, center) of the trees of one block (vid, next, is_center)."""
    ids, stop = table.column("vid").to_numpy(), table.column("is_center").to_numpy()
    order, at = np.argsort(ids), np.arange(len(ids))
    goes = np.flatnonzero(~stop)
    at[goes] = order[np.searchsorted(ids[order], table.column("next").to_numpy()[goes])]
    for _ in range(64):
        if stop[at].all():
            break
        at = at[at]
    else:
        raise RuntimeError("paths did not end")
    return pa.table({"vid": pa.array(ids), "center": pa.array(ids[at])})


def center_of(hops: DataFrame, centers: DataFrame, max_rounds: int = 64, meter: CostMeter | None = None) -> DataFrame:
    """(vid, center): the first center on the way to the primary.

    Whole trees are dealt to tasks; where a tree is larger than ``local.ROWS``, or primaries are not told, by doubling that stops at centers."""
    blocks = _trees_of(hops)
    if blocks:
        marked = hops.select("vid", "primary", F.coalesce("next", "vid").alias("next")).join(centers.select("vid", F.lit(True).alias("is_center")), "vid", "left")
        marked = marked.select("vid", "primary", "next", F.coalesce("is_center", F.lit(False)).alias("is_center"))
        found, seen = measured(_by_tree(marked, blocks).applyInArrow(_first_centers, "vid long, center long"), "center")
        if meter:
            meter.add("center of all", ops=seen["rows"], writes=seen["rows"], rounds=1)
        return found
    marked = hops.join(centers.select("vid", F.lit(True).alias("is_center")), "vid", "left")
    now = materialize(marked.select("vid", F.when(F.coalesce("is_center", F.lit(False)), F.col("vid")).otherwise(F.col("next")).alias("center"), F.coalesce("is_center", F.lit(False)).alias("done")), "center")
    _counted(now, "center of all", meter)
    for _ in range(max_rounds):
        ahead = now.select(F.col("vid").alias("center"), F.col("center").alias("further"), F.col("done").alias("stop"))
        step = now.join(ahead, "center").select("vid", F.col("further").alias("center"), F.col("done"), (F.col("further") != F.col("center")).cast("long").alias("moved"))
        then, seen = measured(step, "center", moved=F.col("moved"))
        if meter:
            meter.add("center of all", ops=seen["rows"], writes=seen["rows"], rounds=1)
        discard(now)
        now = then.select("vid", "center", "done")
        now._scratch_path = then._scratch_path
        if seen["moved"] == 0:
            return now.select("vid", "center")
    raise RuntimeError("paths did not end")


def _split_rows(children_too: bool, k: int):
    """Choose, in one over-full cluster's first vertices, the child subtree nearest to half of k."""

    def pick(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table.column("hop").to_pylist(), table.column("vid").to_pylist(), table.column("next").to_pylist(), table.column("center").to_pylist(), strict=True))
        center = rows[0][3]
        size = {v: 1 for _, v, _, _ in rows}
        for _, v, up, _ in reversed(rows):
            if v != center and up in size:
                size[up] += size[v]
        out = [min((abs(size[v] - k / 2), v) for _, v, _, _ in rows if v != center)[1]]
        if children_too:
            out += [v for _, v, up, _ in rows if up == center and v not in out]
        return pa.table({"vid": pa.array(out, pa.int64())})

    return pick


def split_clusters(hops: DataFrame, centers: DataFrame, k: int, *, mode: str = "recursive", meter: CostMeter | None = None, max_rounds: int = 200) -> DataFrame:
    """(vid) of secondary centers so that no cluster exceeds k.

    ``recursive``: per round, every over-full cluster gives up one subtree out of its first
    k + 1 vertices; ``recursive_children`` also makes the root's children centers;
    ``levelwise``: one bottom-up pass over depths that cuts whenever a residual reaches a threshold."""
    blocks = _trees_of(hops)
    if blocks:
        widest = 0
        if mode == "levelwise":
            widest = hops.filter("next is not null").groupBy("next").count().agg(F.max("count")).head()[0] or 1
        made, seen = measured(_by_tree(hops.select("vid", "primary", "hop", "next"), blocks).applyInArrow(_split_trees(mode, k, widest), "vid long"), "secondaries")
        if meter:
            meter.add("split", ops=hops.count(), writes=seen["rows"], rounds=1)
        return made
    if mode == "levelwise":
        return _levelwise(hops, centers, k)
    # a vertex keeps its center until a new one is made inside its cluster: only over-full clusters are looked at again
    open_, extra = hops, None
    inside = centers.select("vid")
    for _ in range(max_rounds):
        where = _counted(materialize(center_of(open_, inside, meter=meter).join(open_.select("vid", "hop", "next"), "vid"), "clusters"), "clusters", meter)
        full = where.groupBy("center").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > k).select("center")
        over = materialize(where.join(full, "center"), "clusters")
        heads = over.withColumn("rank", F.row_number().over(Window.partitionBy("center").orderBy("hop", "vid"))).filter(F.col("rank") <= k + 1)
        made, seen = measured(heads.select("center", "vid", "hop", "next").groupBy("center").applyInArrow(_split_rows(mode == "recursive_children", k), "vid long"), "secondaries")
        if meter:
            meter.add("split", writes=seen["rows"], rounds=1)
        discard(where)
        if seen["rows"] == 0:
            discard(over)
            return extra if extra is not None else made
        extra = made if extra is None else _counted(materialize(extra.unionByName(made).distinct(), "secondaries"), "split", meter)
        # within an over-full cluster the old center stays where its vertices' paths end
        open_ = over.select("vid", "hop", "next")
        inside = over.select(F.col("center").alias("vid")).unionByName(made).distinct()
    raise RuntimeError("clusters did not shrink")


def _split_trees(mode: str, k: int, widest: int):
    """The secondary centers of whole trees (vid, primary, hop, next), by the rounds' rules: a cluster's first k + 1 vertices tell which subtree it gives up next."""

    def pick(table: pa.Table) -> pa.Table:
        rows = sorted(zip(*(table.column(c).to_pylist() for c in ("hop", "vid", "next")), strict=True))
        kids: dict[int, list[int]] = {}
        for hop, v, up in rows:
            if hop:
                kids.setdefault(up, []).append(v)
        out = []
        if mode == "levelwise":
            limit, below = 1 + (k - 1) // widest, {}
            for hop, v, up in reversed(rows):
                residual = 1 + below.pop(v, 0)
                if hop and residual >= limit:
                    out.append(v)
                elif hop:
                    below[up] = below.get(up, 0) + residual
            return pa.table({"vid": pa.array(out, pa.int64())})
        cut, open_ = set(), [v for hop, v, _ in rows if not hop]
        while open_:
            center = open_[-1]
            heads, level, up = [center], [center], {}
            while level and len(heads) <= k:
                near = sorted((w, v) for v in level for w in kids.get(v, ()) if w not in cut)
                up.update(near)
                level = [w for w, _ in near]
                heads += level
            if len(heads) <= k:
                open_.pop()
                continue
            heads = heads[: k + 1]
            size = dict.fromkeys(heads, 1)
            for v in reversed(heads[1:]):
                size[up[v]] += size[v]
            made = [min((abs(size[v] - k / 2), v) for v in heads[1:])[1]]
            if mode == "recursive_children":
                made += [v for v in heads[1:] if up[v] == center and v not in made]
            cut.update(made)
            out += made
            open_ += made
        return pa.table({"vid": pa.array(out, pa.int64())})

    return pick


def _levelwise(hops: DataFrame, centers: DataFrame, k: int) -> DataFrame:
    """Deepest level first: a vertex whose residual subtree reaches the threshold becomes a center."""
    widest = hops.filter("next is not null").groupBy("next").count().agg(F.max("count")).head()[0] or 1
    limit = 1 + (k - 1) // widest
    deepest = hops.agg(F.max("hop")).head()[0] or 0
    carried, made = None, None
    fixed = centers.select("vid", F.lit(True).alias("is_center"))
    for h in range(deepest, 0, -1):
        level = hops.filter(F.col("hop") == h).join(fixed, "vid", "left")
        if carried is not None:
            level = level.join(carried, "vid", "left").withColumn("residual", F.lit(1) + F.coalesce("below", F.lit(0)))
        else:
            level = level.withColumn("residual", F.lit(1))
        level = materialize(level.select("vid", "next", "residual", (F.col("is_center").isNotNull() | (F.col("residual") >= limit)).alias("cut"), F.col("is_center").isNull().alias("fresh")), "residuals")
        cut = level.filter("cut and fresh").select("vid")
        made = cut if made is None else made.unionByName(cut)
        carried = level.filter("not cut").groupBy(F.col("next").alias("vid")).agg(F.sum("residual").alias("below"))
    return materialize(made, "secondaries") if made is not None else centers.select("vid").limit(0)


@dataclass
class CenterDecomposition:
    graph: Graph
    k: int
    centers: DataFrame  # vid, is_primary: all that asked vertices need
    hops: DataFrame  # one row a vertex, written while building and read by the batch look-up
    implicit: DataFrame  # vid, center of components below k without a primary; written while building, for the batch look-up
    order: str = "vid"
    batch: DataFrame | None = None  # vid, center of all vertices: written when they are first looked up together
    arcs: DataFrame | None = None  # with the centers in arrays, for tasks that search: made when vertices or clusters are first asked for

    def packed_arcs(self) -> DataFrame:
        if self.arcs is None:
            small = self.graph.edges.count() <= local.ROWS
            self.arcs = materialize(searches.packed_arcs(self.graph.edges, self.centers, self.order), "arcs") if small else searches.arcs_in_pieces(self.graph, self.centers, self.order)
        return self.arcs

    def lookup(self, meter: CostMeter | None = None) -> DataFrame:
        """(vid, center, is_implicit) of all vertices, by doubling over the table of next hops."""
        if self.batch is None:
            self.batch = center_of(self.hops, self.centers.select("vid"), meter=meter)
        return self.batch.withColumn("is_implicit", F.lit(False)).unionByName(self.implicit.withColumn("is_implicit", F.lit(True)))

    def cluster_forest(self) -> DataFrame:
        """(vid, center, parent): inside every cluster the tree of paths to its center; a center has no parent."""
        own = self.lookup().join(self.hops.select("vid", "next"), "vid", "left")
        ways = own.select("vid", "center", F.when(F.col("vid") != F.col("center"), F.col("next")).alias("parent"), "is_implicit")
        tree = ways.filter("not is_implicit").select("vid", "center", "parent")
        lone = self.implicit.select(F.col("vid"), F.col("center"))
        if lone.isEmpty():
            return tree
        inside = self.graph.edges.join(lone.select(F.col("vid").alias("a")), "a", "left_semi")
        found = levels(Graph(lone.select("vid"), inside), lone.filter("vid = center").select("vid"), order=self.order)
        return tree.unionByName(found.select("vid", F.col("source").alias("center"), "parent"))

    def materialize(self) -> DataFrame:
        """The explicit baseline: one stored row a vertex."""
        return materialize(self.lookup(), "explicit-centers")


def decompose(graph: Graph, k: int, seed: int = 0, *, mode: str = "recursive", order: str = "vid", meter: CostMeter | None = None) -> CenterDecomposition:
    """Sample, cover components without a primary, split; ``primary_only`` leaves the clusters unsplit.

    ``order`` says which of several neighbours at one distance comes first: the least id, or the least hash of it.

    ``balls`` takes a shifted-ball partition with mean delay k instead: few cut edges, no bound on sizes."""
    graph = graph.fixed()
    if meter:
        meter.add("graph copy", writes=graph.vertices.count() + graph.edges.count())
    if mode == "balls":
        ball = ball_partition(graph, 1.0 / k, seed, meter=meter)
        centers = materialize(ball.filter("hop = 0").select("vid", F.lit(True).alias("is_primary")), "centers")
        return CenterDecomposition(graph, k, centers, ball.select("vid", F.col("source").alias("primary"), "hop", F.col("parent").alias("next")), centers.select("vid", F.col("vid").alias("center")).limit(0))
    primaries = materialize(sample_primaries(graph, k, seed), "primaries")
    hops = next_hops(graph, primaries, meter, order)
    more, implicit = cover_orphans(graph, primaries, hops, k, meter)
    more = _counted(materialize(more, "more-primaries"), "primaries", meter)
    if not more.isEmpty():
        primaries = materialize(primaries.unionByName(more), "primaries")
        hops = materialize(hops.unionByName(_hops_of_orphans(graph, hops, more, meter, order)), "next-hops")
    if meter:
        meter.add("primaries", ops=2 * graph.edges.count(), writes=primaries.count(), rounds=1)
    centers = primaries.withColumn("is_primary", F.lit(True))
    if mode != "primary_only":
        second = split_clusters(hops, primaries, k, mode=mode, meter=meter).join(primaries, "vid", "left_anti")
        centers = centers.unionByName(second.distinct().withColumn("is_primary", F.lit(False)))
    centers, implicit = materialize(centers, "centers"), materialize(implicit, "implicit")
    return CenterDecomposition(graph, k, _counted(centers, "centers", meter), hops, _counted(implicit, "implicit", meter), order)


def check_decomposition(dec: CenterDecomposition) -> DataFrame:
    """One row: vertices without a center, clusters above k, clusters not connected through themselves, centers * k / n."""
    where = materialize(dec.lookup(), "checked")
    sizes = where.groupBy("center").agg(F.count(F.lit(1)).alias("n"))
    lost = dec.graph.vertices.join(where, "vid", "left_anti").count()
    big = sizes.filter(F.col("n") > dec.k).count()
    x, y = where.select(F.col("vid").alias("a"), F.col("center").alias("ca")), where.select(F.col("vid").alias("b"), F.col("center").alias("cb"))
    inner = dec.graph.edges.join(x, "a").join(y, "b").filter("ca = cb").select("a", "b")
    pieces = components_star(Graph(dec.graph.vertices, inner)).select("comp").distinct().count()
    n, c = dec.graph.vertices.count(), sizes.count()
    return dec.graph.vertices.sparkSession.createDataFrame([(lost, big, abs(pieces - c), round(dec.centers.count() * dec.k / max(1, n), 3))], "lost long, oversized long, broken long, centers_k_over_n double")


# --- implicit look-ups ----------------------------------------------------------------------------


def lookup_center(dec: CenterDecomposition, asked: DataFrame, max_hops: int = 10_000, meter: CostMeter | None = None, costs: bool = False) -> DataFrame:
    """(vid, center; with ``costs`` the vertices visited) of the asked vertices only: each searches outward until its level holds a primary, then walks to the first center.

    A vertex of level i that leads on to a primary of level h is h - i hops from its nearest primary,
    and its neighbours one hop nearer are exactly those of level i + 1 that lead on too: the least
    of them is the next hop.  A search that ends without a primary has seen a whole component,
    whose least vertex is its center.  Only centers and arcs are read; a question's levels are its own,
    O(k log n) vertices of which its walk is settled in one task, and nothing of them is kept.  Arcs of up to
    ``searches.HELD`` edges go to every task as arrays, which searches for a share of the questions."""
    if searches.is_held(dec.graph):
        found, told = measured(_searches(dec, asked), "looked-up", looked=F.col("looked"))
        if meter:
            meter.add("look-up", ops=told["rows"] + told["looked"], scratch_peak=told["rows"] + told["looked"])
            meter.add("look-up", writes=told["rows"])
        return found.select("vid", "center", "visited") if costs else found.select("vid", "center")
    primary = dec.centers.filter("is_primary").select(F.col("vid").alias("at"), F.lit(True).alias("hit"))
    marked = lambda df, level: df.join(primary, "at", "left").select("qid", "at", F.coalesce("hit", F.lit(False)).alias("hit"), F.lit(level).alias("level"))
    with adjacency(dec.graph) as arcs:
        front, seen = measured(marked(asked.select(F.col("vid").alias("qid")).distinct().withColumn("at", F.col("qid")), 0), "look")
        levels_, ops = [front], seen["rows"]
        for level in range(1, max_hops):
            # neighbours of a level lie in it, in the one before or in the next one
            known = front.select("qid", "at") if level == 1 else front.select("qid", "at").unionByName(levels_[-2].select("qid", "at"))
            going = front.join(front.filter("hit").select("qid").distinct(), "qid", "left_anti")
            sent, looked = watched(going.select("qid", F.col("at").alias("src")).join(arcs.select("src", "dst"), "src"))
            step = sent.select("qid", F.col("dst").alias("at")).distinct().join(known, ["qid", "at"], "left_anti")
            front, seen = measured(marked(step, level), "look")
            ops += looked.rows
            if seen["rows"] == 0:
                break
            levels_.append(front)
        visited = levels_[0]
        for more in levels_[1:]:
            visited = visited.unionByName(more)
        rank = F.col("dst") if dec.order == "vid" else F.xxhash64("dst")
        onward = visited.select("qid", F.col("at").alias("src"), "level").join(arcs.select("src", "dst"), "src") \
            .join(visited.select("qid", F.col("at").alias("dst"), (F.col("level") - 1).alias("level")), ["qid", "dst", "level"]).select("qid", "src", "dst", "level", rank.alias("rank"))
        onward = materialize(onward, "look-onward")
        stops = visited.join(dec.centers.select(F.col("vid").alias("at"), F.lit(True).alias("stop")), "at", "left").select("qid", "at", "level", "hit", F.coalesce("stop", F.lit(False)).alias("stop"))
        blocks = max(1, sum(x.count() for x in levels_) // LOOK_ROWS + 1)
        dealt = lambda df: df.withColumn("block", F.pmod(F.xxhash64("qid"), F.lit(blocks)).cast("int")).groupBy("block")
        found, told = measured(dealt(stops).cogroup(dealt(onward)).applyInArrow(_settled, "vid long, center long, visited long"), "looked-up")
        if meter:
            meter.add("look-up", ops=ops, scratch_peak=ops)
            meter.add("look-up", writes=told["rows"])
        discard(onward, *levels_)
    return found if costs else found.select("vid", "center")


def _searches(dec: CenterDecomposition, asked: DataFrame, share: int = 100_000) -> DataFrame:
    """(vid, center, visited, looked) of the asked vertices, each by its own search over arcs that every task holds."""
    asked = asked.select("vid").distinct()
    shares = _shares(asked, share)
    if dec.graph.edges.count() > local.ROWS:  # every share moves all arcs: one a core
        shares = min(shares, asked.sparkSession.sparkContext.defaultParallelism)
    return searches.by_share(asked, dec.packed_arcs(), shares, searches.looked_up, "vid long, center long, visited long, looked long")


def _shares(asked: DataFrame, share: int) -> int:
    return max(1, min(width(asked), asked.count() // share + 1))


def _settled(visited: pa.Table, onward: pa.Table) -> pa.Table:
    """(vid, center, visited) of the questions of one block, from what their searches met and the arcs that lead outward."""
    met: dict[int, dict[int, tuple]] = {}
    for q, at, level, hit, stop in zip(*(visited.column(c).to_pylist() for c in ("qid", "at", "level", "hit", "stop")), strict=True):
        met.setdefault(q, {})[at] = (level, hit, stop)
    ways: dict[int, list[tuple]] = {}
    for q, src, dst, level, rank in zip(*(onward.column(c).to_pylist() for c in ("qid", "src", "dst", "level", "rank")), strict=True):
        ways.setdefault(q, []).append((level, src, rank, dst))
    out = []
    for q, seen in met.items():
        leads = {at for at, (_, hit, _) in seen.items() if hit}
        if not leads:
            out.append((q, min(seen), len(seen)))
            continue
        after: dict[int, tuple] = {}
        for _, src, rank, dst in sorted(ways.get(q, ()), key=lambda w: -w[0]):  # from the primaries' level back
            if dst in leads and (src not in after or (rank, dst) < after[src]):
                after[src] = (rank, dst)
                leads.add(src)
        at = q
        while not seen[at][2]:
            at = after[at][1]
        out.append((q, at, len(seen)))
    columns = list(zip(*out, strict=True)) or [(), (), ()]
    return pa.table([pa.array(c, pa.int64()) for c in columns], names=["vid", "center", "visited"])


def met_of(dec: CenterDecomposition, centers: DataFrame, meter: CostMeter | None = None, share: int = 10_000) -> DataFrame:
    """(center, vid, own): the vertices that searches outward from the centers of the asked clusters meet, each with the center that its own look-up tells.

    A cluster hangs together through itself, so that no search leaves it by more than a hop: what is met are the members and all their
    neighbours.  Below ``local.ROWS`` edges tasks that hold the arcs take a share of the clusters each; else a vertex that several
    searches meet is looked up once."""
    centers = centers.select("center").distinct()
    if dec.graph.edges.count() <= local.ROWS:
        asked = materialize(centers.select(F.col("center").alias("vid")), "asked-centers")
        found, told = measured(searches.by_share(asked, dec.packed_arcs(), _shares(asked, share), searches.met, "center long, vid long, own long, ops long"), "met", ops=F.col("ops"))
        if meter:
            meter.add("look-up", ops=told["ops"], writes=told["rows"], scratch_peak=told["ops"])
        return found.select("center", "vid", "own")
    front = materialize(centers.select("center", F.col("center").alias("vid")), "members")
    met, known = front.select("center", "vid", F.col("center").alias("own")), None
    with adjacency(dec.graph) as arcs:
        while True:
            out = front.join(arcs.select(F.col("src").alias("vid"), F.col("dst")), "vid").select("center", F.col("dst").alias("vid")).distinct()
            fresh, seen = measured(out.join(met.select("center", "vid"), ["center", "vid"], "left_anti"), "members-near")
            if seen["rows"] == 0:
                return met
            new = fresh.select("vid").distinct()
            told = lookup_center(dec, new if known is None else new.join(known, "vid", "left_anti"), meter=meter)
            known = told if known is None else known.unionByName(told)
            found = materialize(fresh.join(known.withColumnRenamed("center", "own"), "vid").select("center", "vid", "own"), "met")
            met, front = met.unionByName(found), found.filter("own = center").select("center", "vid")


def members_of(dec: CenterDecomposition, centers: DataFrame, meter: CostMeter | None = None) -> DataFrame:
    """(center, vid) of the asked clusters, by searches outward from their centers: a neighbour belongs if its own look-up says so."""
    return met_of(dec, centers, meter).filter("own = center").select("center", "vid")


def members_of_all(dec: CenterDecomposition) -> DataFrame:
    """(center, vid) of all clusters, from the batch look-up."""
    return dec.lookup().select("center", "vid")


def quotient(graph: Graph, where: DataFrame) -> DataFrame:
    """(ca, cb, mult, rep_a, rep_b): the multigraph of clusters with one original edge for each pair; a plan, never stored here."""
    x, y = where.select(F.col("vid").alias("a"), F.col("center").alias("xa")), where.select(F.col("vid").alias("b"), F.col("center").alias("xb"))
    rows = graph.edges.join(x, "a").join(y, "b").filter("xa <> xb")
    return rows.groupBy(F.least("xa", "xb").alias("ca"), F.greatest("xa", "xb").alias("cb")).agg(F.sum("mult").cast("int").alias("mult"), F.min(F.struct("a", "b")).alias("rep")).select("ca", "cb", "mult", F.col("rep.a").alias("rep_a"), F.col("rep.b").alias("rep_b"))


def quotient_neighbors(dec: CenterDecomposition, centers: DataFrame | None = None, meter: CostMeter | None = None) -> DataFrame:
    """(center, neighbor) of the asked clusters, through the far ends of their members' edges, whose look-ups their searches took; of all clusters in one batch."""
    if centers is not None:
        return met_of(dec, centers, meter).filter("own <> center").select("center", F.col("own").alias("neighbor")).distinct()
    named = dec.lookup()
    out = materialize(named.select("center", F.col("vid").alias("src")).join(dec.graph.arcs(), "src").select("center", F.col("dst").alias("vid")).distinct(), "outward")
    return out.join(named.select("vid", F.col("center").alias("neighbor")), "vid").filter("center <> neighbor").select("center", "neighbor").distinct()
