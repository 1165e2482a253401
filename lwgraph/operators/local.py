"""The last rounds of iterative methods: once few rows are left, one task ends what a round of jobs would only shorten.

Every function here gets at most ``ROWS`` rows, or arcs of as many edges; the callers count before they come."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROWS = 1 << 21  # of at most four whole numbers each
CORPUS_ROWS = 1 << 16  # for contractions beside texts
LABELLED = "vid long, parent long, root long, first long, last long, idx long, size long, depth int, low long, high long, separating boolean, block long, head_vid long, members long"


def forest_arrays(u: np.ndarray, v: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(least vertex of each vertex's component, whether each edge is in the forest) for edges over 0 .. n - 1."""
    root, chosen = np.arange(n, dtype=np.int32 if u.dtype == np.int32 else np.int64), np.zeros(len(u), bool)
    live = np.arange(len(u), dtype=root.dtype)
    while True:
        u, v = root[u], root[v]
        open_ = u != v
        live, u, v = live[open_], u[open_], v[open_]
        if not len(live):
            return root, chosen
        low, high, hook = np.minimum(u, v), np.maximum(u, v), root.copy()
        np.minimum.at(hook, high, low)  # each root hooks onto its least neighbour
        least = np.flatnonzero(low == hook[high])[::-1]
        way = np.full(n, -1, root.dtype)
        way[high[least]] = live[least]  # of equal edges the first is written last
        root, first = hook, way[way >= 0]
        chosen[first] = True
        while (root[root] != root).any():
            root = root[root]


def local_forest(edges: DataFrame) -> DataFrame:
    """(vid, root, ra, rb) of edges (a, b, rep): a row a vertex, and a row with the representative of each forest edge."""

    def run(table: pa.Table) -> pa.Table:
        a, b = table.column("a").to_numpy(), table.column("b").to_numpy()
        order = np.lexsort((b, a))
        a, b = a[order], b[order]
        names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        root, chosen = forest_arrays(at[: len(a)], at[len(a) :], len(names))
        ra, rb = (table.column(c).to_numpy()[order][chosen] for c in ("ra", "rb"))
        none = lambda n: pa.nulls(n, pa.int64())
        return pa.table({"vid": pa.concat_arrays([pa.array(names, pa.int64()), none(len(ra))]), "root": pa.concat_arrays([pa.array(names[root], pa.int64()), none(len(ra))]),
                         "ra": pa.concat_arrays([none(len(names)), pa.array(ra, pa.int64())]), "rb": pa.concat_arrays([none(len(names)), pa.array(rb, pa.int64())])})

    return edges.select("a", "b", "ra", "rb").groupBy(F.lit(0).alias("one")).applyInArrow(run, "vid long, root long, ra long, rb long")


def local_ranks(links: DataFrame) -> DataFrame:
    """(id, left) of links (id, next, step): the sum of steps from each id to the end of its list, its own included."""

    def run(table: pa.Table) -> pa.Table:
        ids, after, step = table.column("id").to_numpy(), table.column("next"), table.column("step").to_numpy().copy()
        order = np.argsort(ids)
        last = after.is_null().to_numpy()
        at = np.arange(len(ids))
        at[~last] = order[np.searchsorted(ids[order], after.drop_null().to_numpy())]
        left, ended = step.copy(), last.copy()
        while not ended.all():
            left = left + np.where(ended, 0, left[at])
            ended, at = ended | ended[at], np.where(ended, at, at[at])
        return pa.table({"id": pa.array(ids, pa.int64()), "left": pa.array(left, pa.int64())})

    return links.select("id", "next", "step").groupBy(F.lit(0).alias("one")).applyInArrow(run, "id long, left long")


def local_tops(rows: DataFrame) -> DataFrame:
    """(id, top, most) of rows (id, up, value): the row without an ``up`` that each leads to, and the largest value on the way, both ends included."""

    def run(table: pa.Table) -> pa.Table:
        ids, most = table.column("id").to_numpy(), table.column("value").to_numpy().copy()
        order, has = np.argsort(ids), table.column("up").is_valid().to_numpy()
        at, up = np.arange(len(ids)), table.column("up").drop_null().to_numpy()
        spot = order[np.minimum(np.searchsorted(ids[order], up), len(ids) - 1)]
        at[has] = np.where(ids[spot] == up, spot, at[has])  # a row that is not there is no way on
        last = at == np.arange(len(ids))
        for _ in range(64):
            if last[at].all():
                break
            most, at = np.maximum(most, most[at]), at[at]
        else:
            raise RuntimeError("not a forest")
        return pa.table({"id": pa.array(ids, pa.int64()), "top": pa.array(ids[at], pa.int64()), "most": pa.array(np.maximum(most, most[at]), pa.int64())})

    return rows.select("id", "up", "value").groupBy(F.lit(0).alias("one")).applyInArrow(run, "id long, top long, most long")


def local_levels(arcs: DataFrame, front: DataFrame) -> DataFrame:
    """(vid, source, hop, parent) of vertices that a search reaches from its frontier (vid, source), hops counted from there.

    arcs (vid, near, rank) are those of all vertices not yet reached; of the neighbours one level nearer the one of least rank leads."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        names, at = np.unique(np.concatenate([*(left.column(c).to_numpy() for c in ("vid", "near")), right.column("vid").to_numpy()]), return_inverse=True)
        n, m = len(names), left.num_rows
        vid, near, start = at[:m], at[m : 2 * m], at[2 * m :]
        hop, parent, source = np.full(n, -1, np.int32), np.zeros(n, np.int64), np.zeros(n, np.int64)
        hop[start], source[start] = 0, right.column("source").to_numpy()
        order = np.lexsort((near, left.column("rank").to_numpy(), vid))
        vid, near, level = vid[order], near[order], 0
        while True:
            found = np.flatnonzero(hop[near] == level)
            found = found[np.concatenate([[True], vid[found][1:] != vid[found][:-1]])] if len(found) else found
            if not len(found):
                break
            level += 1
            hop[vid[found]], parent[vid[found]], source[vid[found]] = level, names[near[found]], source[near[found]]
            open_ = hop[vid] < 0
            vid, near = vid[open_], near[open_]
        out = np.flatnonzero(hop > 0)
        return pa.table({"vid": pa.array(names[out], pa.int64()), "source": pa.array(source[out], pa.int64()), "hop": pa.array(hop[out], pa.int32()), "parent": pa.array(parent[out], pa.int64())})

    one = F.lit(0).alias("one")
    return arcs.select("vid", "near", "rank").groupBy(one).cogroup(front.select("vid", "source").groupBy(one)).applyInArrow(run, "vid long, source long, hop int, parent long")


def steps_left(after: np.ndarray, ended: np.ndarray, spread: int = 64) -> np.ndarray:
    """Steps from each place to the end of its list, by the place that follows; lists end where ``ended``.

    Some places, and all that nothing leads to, begin stretches; each walks on to where the next one begins, all together, and only
    these are ranked by doubling."""
    begins = np.random.default_rng(0).integers(0, spread, len(after), np.uint8) == 0
    led = np.zeros(len(after), bool)
    led[after[~ended]] = True
    begins |= ~led
    at = np.flatnonzero(begins)
    who, own, off = np.arange(len(at)), np.zeros(len(after), np.int32), np.zeros(len(after), np.int32)
    own[at] = who
    gap, then, t = np.zeros(len(at), np.int64), who.copy(), 0
    while len(at):
        last = ended[at]
        gap[who[last]] = t
        at, who, t = after[at[~last]], who[~last], t + 1
        met = begins[at]
        gap[who[met]], then[who[met]] = t, own[at[met]]
        at, who = at[~met], who[~met]
        own[at], off[at] = who, t
    done = then == np.arange(len(then))
    while not done.all():
        gap = gap + np.where(done, 0, gap[then])
        done, then = done | done[then], np.where(done, then, then[then])
    return gap[own] - off


def rooted_arrays(a: np.ndarray, b: np.ndarray, root: np.ndarray) -> dict[str, np.ndarray]:
    """parent (-1 at roots), first, last, idx, size and depth of the forest a - b over 0 .. n - 1 with the least vertex of every tree."""
    n, m, src, dst = len(root), len(a), np.concatenate([a, b]), np.concatenate([b, a])
    members = np.bincount(root, minlength=n)
    ring = np.argsort(src.astype(np.int64) * n + dst)
    opens = np.concatenate([[True], src[ring][1:] != src[ring][:-1]])[: 2 * m]
    wraps, then = np.zeros(2 * m, bool), np.zeros(2 * m, np.int64)
    wraps[ring] = np.concatenate([opens[1:], [True]])[: 2 * m]
    then[ring] = np.where(wraps[ring], ring[np.flatnonzero(opens)][np.cumsum(opens) - 1] if m else 0, np.roll(ring, -1))
    back = np.concatenate([np.arange(m, 2 * m), np.arange(m)])  # the arc after (u, v) is the one after (v, u) around v
    ended = wraps[back] & (root[dst] == dst)
    pos = 2 * members[root[src]] - 2 - steps_left(then[back], ended)
    down = pos < pos[back]
    first, last, parent = np.zeros(n, np.int64), 2 * members[root] - 1, np.full(n, -1)
    first[dst[down]], last[dst[down]], parent[dst[down]] = pos[down], pos[back][down], src[down]
    idx = np.empty(n, np.int64)
    idx[np.argsort(root.astype(np.int64) * (2 * n) + first)] = np.arange(n)
    return {"parent": parent, "first": first, "last": last, "idx": idx, "size": (last - first + 1) // 2, "depth": (2 * (idx - idx[root]) - first).astype(np.int32)}


def labelled_arrays(a: np.ndarray, b: np.ndarray, parent: np.ndarray, idx: np.ndarray, size: np.ndarray) -> dict[str, np.ndarray]:
    """low, high, separating, block (-1 at roots), and by block its head and number of members, of the different edges a - b over a rooted forest:
    the rules of ``blocks.block_labelling``."""
    n, up = len(parent), np.maximum(parent, 0)
    beside = (parent[a] != b) & (parent[b] != a)
    a, b = a[beside], b[beside]
    low, high = np.arange(n), np.arange(n)  # by number
    np.minimum.at(low, idx[a], idx[b])
    np.minimum.at(low, idx[b], idx[a])
    np.maximum.at(high, idx[a], idx[b])
    np.maximum.at(high, idx[b], idx[a])
    low, high = range_least(low, high, idx, idx + size - 1)
    under = parent >= 0
    separating = under & (low >= idx[up]) & (high < idx[up] + size[up])
    holds = lambda x, y: (idx[x] <= idx[y]) & (idx[y] < idx[x] + size[x])
    cross = ~holds(a, b) & ~holds(b, a)
    joined = np.flatnonzero(under & ~separating)
    block, _ = forest_arrays(np.concatenate([joined, a[cross]]), np.concatenate([parent[joined], b[cross]]), n)
    members, head = np.bincount(block[under], minlength=n), np.full(n, -1)
    late = np.flatnonzero(under)[np.argsort(-idx[under], kind="stable")]
    head[block[late]] = parent[late]  # the earliest member is written last
    return {"low": low, "high": high, "separating": separating, "block": np.where(under, block, -1), "head": head, "members": members}


def _ids(names: np.ndarray, at: np.ndarray) -> pa.Array:
    """The names at given places, null below 0."""
    return pa.array(names[at] if len(names) else np.zeros(len(at), np.int64), pa.int64(), mask=at < 0)


def local_root_forest(tree: DataFrame, comp: DataFrame) -> DataFrame:
    """(vid, parent, root, first, last, idx, size, depth) of the forest (a, b) with components (vid, comp): circuit, ranks and numbering as ``blocks.root_forest`` has them."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        order = np.argsort(right.column("vid").to_numpy())
        names = right.column("vid").to_numpy()[order]
        root = np.searchsorted(names, right.column("comp").to_numpy()[order])
        made = rooted_arrays(*(np.searchsorted(names, left.column(c).to_numpy()) for c in ("a", "b")), root)
        return pa.table({"vid": _ids(names, np.arange(len(names))), "parent": _ids(names, made["parent"]), "root": _ids(names, root),
                         **{c: pa.array(made[c]) for c in ("first", "last", "idx", "size", "depth")}})

    one = F.lit(0).alias("one")
    return tree.select("a", "b").groupBy(one).cogroup(comp.select("vid", "comp").groupBy(one)).applyInArrow(run, "vid long, parent long, root long, first long, last long, idx long, size long, depth int")


def local_labelling(edges: DataFrame, forest: DataFrame) -> DataFrame:
    """Rows of a rooted forest with low, high, separating (null at roots) and block; the row that a block is named by also has its head_vid and members."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.take(pa.array(np.argsort(right.column("vid").to_numpy())))
        names = right.column("vid").to_numpy()
        parent, under = np.full(len(names), -1), right.column("parent").is_valid().to_numpy()
        parent[under] = np.searchsorted(names, right.column("parent").drop_null().to_numpy())
        made = labelled_arrays(*(np.searchsorted(names, left.column(c).to_numpy()) for c in ("a", "b")), parent, right.column("idx").to_numpy(), right.column("size").to_numpy())
        return pa.table({**{c: right.column(c) for c in right.column_names if c != "one"}, "low": pa.array(made["low"]), "high": pa.array(made["high"]), "separating": pa.array(made["separating"], mask=~under),
                         "block": _ids(names, made["block"]), "head_vid": _ids(names, made["head"]), "members": pa.array(made["members"], mask=made["head"] < 0)})

    one, kept = F.lit(0).alias("one"), ("vid", "parent", "root", "first", "last", "idx", "size", "depth")
    return edges.select("a", "b").groupBy(one).cogroup(forest.select(*kept).groupBy(one)).applyInArrow(run, LABELLED)


def local_whole_labelling(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """The rows of ``local_labelling`` from vertices (vid) and different edges (a, b): forest, circuit and labels in one task."""
    one = F.lit(0).alias("one")
    return edges.select("a", "b").groupBy(one).cogroup(vertices.select("vid").groupBy(one)).applyInArrow(_whole_labelling, LABELLED)


def labelled_components(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """The same for whole components dealt to the tasks of a ``share`` each: vertices (vid, share, base) with the numbers of their component from ``base`` on, edges (a, b, share)."""
    return edges.select("a", "b", "share").groupBy("share").cogroup(vertices.select("vid", "base", "share").groupBy("share")).applyInArrow(_whole_labelling, LABELLED)


def _whole_labelling(left: pa.Table, right: pa.Table) -> pa.Table:
    sorted_ = np.argsort(right.column("vid").to_numpy())
    names = right.column("vid").to_numpy()[sorted_]
    a, b = (np.searchsorted(names, left.column(c).to_numpy()) for c in ("a", "b"))
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    root, chosen = forest_arrays(a, b, len(names))
    tree = rooted_arrays(a[chosen], b[chosen], root)
    made = labelled_arrays(a, b, tree["parent"], tree["idx"], tree["size"])
    if "base" in right.column_names:  # other tasks number other components
        moved = right.column("base").to_numpy()[sorted_] - tree["idx"][root]
        tree["idx"], made["low"], made["high"] = tree["idx"] + moved, made["low"] + moved, made["high"] + moved
    return pa.table({"vid": pa.array(names, pa.int64()), "parent": _ids(names, tree["parent"]), "root": _ids(names, root), **{c: pa.array(tree[c]) for c in ("first", "last", "idx", "size", "depth")},
                     "low": pa.array(made["low"]), "high": pa.array(made["high"]), "separating": pa.array(made["separating"], mask=tree["parent"] < 0),
                     "block": _ids(names, made["block"]), "head_vid": _ids(names, made["head"]), "members": pa.array(made["members"], mask=made["head"] < 0)})


def bridge_arrays(a: np.ndarray, b: np.ndarray, single: np.ndarray, n: int) -> np.ndarray:
    """Which of the different edges a - b over 0 .. n - 1 are bridges: tree edges without a copy whose subtree no other edge leaves."""
    root, chosen = forest_arrays(a, b, n)
    tree = rooted_arrays(a[chosen], b[chosen], root)
    del root
    parent, idx, size = tree["parent"], tree["idx"], tree["size"]
    del tree
    low, high = np.arange(n), np.arange(n)  # by number
    x, y = idx[a[~chosen]], idx[b[~chosen]]
    for low_, high_ in ((x, y), (y, x)):
        np.minimum.at(low, low_, high_)
        np.maximum.at(high, low_, high_)
    del x, y
    cut = np.flatnonzero(chosen & single)
    lower = np.where(parent[a[cut]] == b[cut], a[cut], b[cut])
    first = idx[lower]
    last = first + size[lower] - 1
    low, high = range_least(low, high, first, last)
    out = np.zeros(len(a), bool)
    out[cut[(low >= first) & (high <= last)]] = True
    return out


def local_bridges(edges: DataFrame, key) -> DataFrame:
    """(key, a, b): the bridges among edges (a, b, mult) of many graphs, the edges of each under its own ``key`` and in one task."""

    def run(table: pa.Table) -> pa.Table:
        a, b, mult = (table.column(c).to_numpy() for c in ("a", "b", "mult"))
        names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        cut = bridge_arrays(at[: len(a)], at[len(a) :], mult == 1, len(names))
        return pa.table({"key": table.column("key").filter(pa.array(cut)), "a": pa.array(a[cut]), "b": pa.array(b[cut])})

    return edges.select(key.cast("int").alias("key"), "a", "b", "mult").groupBy("key").applyInArrow(run, "key int, a long, b long")


def sampled_bridges(edges: DataFrame, n: int, samples: int, partitions: int) -> DataFrame:
    """(key, a, b): the bridges of many samples of one graph, edges (a, b, mult, held) between places 0 .. n - 1 with bit i of ``held`` for those of sample i.

    An edge is dealt out in arrays of nine bytes a sample that holds it, and each sample is one task's."""

    def deal(batches):
        for batch in batches:
            a, b = (batch.column(c).to_numpy().astype(np.int32) for c in ("a", "b"))
            single, held = batch.column("mult").to_numpy() == 1, batch.column("held").to_numpy()
            for i in range(samples):
                mine = (held >> i) & 1 == 1
                row = [pa.array([i], pa.int32()), *(pa.array([x[mine].tobytes()], pa.binary()) for x in (a, b, single))]
                yield pa.RecordBatch.from_arrays(row, names=["key", "a", "b", "single"])

    def run(table: pa.Table) -> pa.Table:
        a, b, single = (np.concatenate([np.frombuffer(x.as_buffer(), kind) for x in table.column(c).combine_chunks()]) for c, kind in (("a", np.int32), ("b", np.int32), ("single", bool)))
        cut = bridge_arrays(a, b, single, n)
        return pa.table({"key": pa.array(np.full(int(cut.sum()), table.column("key")[0].as_py(), np.int32)), "a": pa.array(a[cut]), "b": pa.array(b[cut])})

    dealt = edges.select("a", "b", "mult", "held").mapInArrow(deal, "key int, a binary, b binary, single binary")
    return dealt.repartition(partitions, "key").groupBy("key").applyInArrow(run, "key int, a int, b int")


def local_climbs(pairs: DataFrame, parents: DataFrame, opens: DataFrame) -> DataFrame:
    """(qid, cluster, pu, pv, ok) of pairs (qid, pu, cu, pv, cv) that meet in one cluster, by the walk of ``same_block_step_by_step``:
    clusters (cluster, parent, depth) and open bits (cluster, point, open) go to every task, which takes a share of the pairs."""
    blocks = max(1, min(int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions")), pairs.count() // 200_000 + 1))
    every = _climbed(parents, opens).withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    dealt = pairs.select("qid", "pu", "cu", "pv", "cv", F.pmod(F.xxhash64("qid"), F.lit(blocks)).cast("int").alias("share"))
    return _climbs(dealt, every)


def tree_climbs(pairs: DataFrame, parents: DataFrame, opens: DataFrame, share: int = 1 << 18) -> DataFrame:
    """The same with whole trees of clusters dealt to tasks, each with the pairs inside them; parents also have their ``root``.  Two trees have no way between them."""
    blocks = opens.count() // share + 1
    tree = lambda c, root="root": parents.select(F.col("cluster").alias(c), F.col("root").alias(root))
    part = lambda root: F.pmod(F.xxhash64(root), F.lit(blocks)).cast("int").alias("share")
    every = _climbed(parents, opens).join(tree("cluster"), "cluster").select("cluster", "parent", "depth", "point", part("root"))
    dealt = pairs.join(tree("cu", "ru"), "cu").join(tree("cv", "rv"), "cv").filter("ru = rv").select("qid", "pu", "cu", "pv", "cv", part("ru"))
    return _climbs(dealt, every)


def _climbed(parents: DataFrame, opens: DataFrame) -> DataFrame:
    none = F.lit(None).cast("bigint")
    return parents.select("cluster", "parent", F.col("depth").cast("long").alias("depth"), none.alias("point")).unionByName(opens.filter("open").select("cluster", none.alias("parent"), none.alias("depth"), "point"))


def _climbs(dealt: DataFrame, every: DataFrame) -> DataFrame:
    return dealt.groupBy("share").cogroup(every.groupBy("share")).applyInArrow(_climb_share, "qid long, cluster long, pu long, pv long, ok boolean")


def _climb_share(pairs: pa.Table, every: pa.Table) -> pa.Table:
    is_open = every.column("depth").is_null()
    held, bits = every.filter(pa.compute.invert(is_open)), every.filter(is_open)
    order = np.argsort(held.column("cluster").to_numpy())
    names, depth = held.column("cluster").to_numpy()[order], held.column("depth").to_numpy()[order]
    parent = held.column("parent").take(pa.array(order))
    up = np.full(len(names), -1)
    up[parent.is_valid().to_numpy()] = np.searchsorted(names, parent.drop_null().to_numpy())
    point, spot = bits.column("point").to_numpy(), np.searchsorted(names, bits.column("cluster").to_numpy())
    points = np.unique(np.concatenate([point, -1 - names, pairs.column("pu").to_numpy(), pairs.column("pv").to_numpy()]))
    width = len(points)
    known = np.sort(spot * width + np.searchsorted(points, point))
    port = np.searchsorted(points, -1 - names)

    def opened(c, p):
        at = c * width + p
        return known[np.minimum(np.searchsorted(known, at), len(known) - 1)] == at if len(known) else np.zeros(len(c), bool)

    q = pairs.column("qid").to_numpy()
    cu, cv = (np.searchsorted(names, pairs.column(c).to_numpy()) for c in ("cu", "cv"))
    pu, pv = (np.searchsorted(points, pairs.column(c).to_numpy()) for c in ("pu", "pv"))
    ok, out = np.ones(len(q), bool), []
    while len(q):
        met = cu == cv
        out.append((q[met], names[cu[met]], points[pu[met]], points[pv[met]], ok[met]))
        climbs = depth[cu] >= depth[cv]  # the deeper end climbs
        low, at = np.where(climbs, cu, cv), np.where(climbs, pu, pv)
        going = ~met & (up[low] >= 0)  # at a root there is no way on
        q, cu, cv, pu, pv, ok, climbs, low, at = (x[going] for x in (q, cu, cv, pu, pv, ok, climbs, low, at))
        ok = ok & opened(low, at)
        cu, cv, pu, pv = np.where(climbs, up[low], cu), np.where(climbs, cv, up[low]), np.where(climbs, port[low], pu), np.where(climbs, pv, port[low])
    q, c, pu, pv, ok = (np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 4 + (np.zeros(0, bool),)
    return pa.table({"qid": pa.array(q), "cluster": pa.array(c), "pu": pa.array(pu), "pv": pa.array(pv), "ok": pa.array(ok)})


def range_least(low: np.ndarray, high: np.ndarray, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(least of ``low``, greatest of ``high``) over the positions first .. last of every question, by a sparse table."""
    out_l, out_h = np.zeros(len(first), low.dtype), np.zeros(len(first), high.dtype)
    level = np.frexp((last - first + 1).astype(float))[1] - 1  # whole part of the logarithm
    for j in range(int(level.max(initial=-1)) + 1):
        if j:
            half = 1 << (j - 1)
            low, high = np.minimum(low[:-half], low[half:]), np.maximum(high[:-half], high[half:])
        at = np.flatnonzero(level == j)
        a, b = first[at], last[at] - (1 << j) + 1
        out_l[at], out_h[at] = np.minimum(low[a], low[b]), np.maximum(high[a], high[b])
    return out_l, out_h


def local_ranges(rows: DataFrame, asked: DataFrame, block: str) -> DataFrame:
    """(id, lo, hi) of questions (id, first, last) that stay inside one ``block`` of rows (idx, lo, hi); rows of a block follow each other."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        idx = left.column("idx").to_numpy()
        if not len(idx):
            return pa.table({"id": pa.array([], pa.int64()), "lo": pa.array([], pa.int64()), "hi": pa.array([], pa.int64())})
        order = np.argsort(idx)
        base = idx[order[0]]
        lo, hi = range_least(left.column("lo").to_numpy()[order], left.column("hi").to_numpy()[order], right.column("first").to_numpy() - base, right.column("last").to_numpy() - base)
        return pa.table({"id": right.column("id"), "lo": pa.array(lo, pa.int64()), "hi": pa.array(hi, pa.int64())})

    return rows.select(block, "idx", "lo", "hi").groupBy(block).cogroup(asked.select(block, "id", "first", "last").groupBy(block)).applyInArrow(run, "id long, lo long, hi long")
