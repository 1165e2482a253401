"""Searches of asked vertices and clusters by arrays: tasks hold the arcs of a graph and search for a share of the questions.

Arcs are four arrays: names in order, where the neighbours of each begin, their places by rank, and kinds (2 a primary, 1 another
center).  Those of up to ``local.ROWS`` edges are packed in one task, a row each; those of up to ``HELD`` edges in pieces of consecutive
vertices, which whoever reads them puts together.  The searches of some thousands of questions go level by level together; each sees only its own levels."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.graph import Graph
from ..plans.scratch import materialize
from .trees import global_index

HELD = 1 << 24  # edges whose arcs a task may hold: four bytes an arc, thirteen a vertex
PIECE = 1 << 20  # arcs to a piece
CHUNK = 1 << 13  # questions that are searched for together
MOST = 1 << 23  # arcs that a level looks at together; beyond, fewer questions at once
PACKED = "what string, piece int, held binary"


def packed_arcs(edges: DataFrame, centers: DataFrame, order: str) -> DataFrame:
    """The arrays (what, held) of edges (a, b) and centers (vid, is_primary); neighbours by id, or with ``order="hash"`` by a hash of it."""

    def pack(left: pa.Table, right: pa.Table) -> pa.Table:
        a, b, ra, rb = (left.column(c).to_numpy() for c in ("a", "b", "ra", "rb"))
        names, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        src, dst = at, np.concatenate([at[len(a) :], at[: len(a)]])
        near = dst[np.lexsort((dst, np.concatenate([rb, ra]), src))]
        many = np.bincount(src, minlength=len(names))
        vid, kinds = right.column("vid").to_numpy(), np.zeros(len(names), np.int8)
        known = among(names, vid)
        kinds[np.searchsorted(names, vid[known])] = np.where(right.column("is_primary").to_numpy(zero_copy_only=False)[known], 2, 1)
        return _piece(0, names=names.astype(np.int64), many=many.astype(np.int32), near=near.astype(np.int32), kinds=kinds)

    rank = (lambda c: F.col(c)) if order == "vid" else F.xxhash64
    one = F.lit(0).alias("one")
    return edges.select("a", "b", rank("a").alias("ra"), rank("b").alias("rb")).groupBy(one).cogroup(centers.select("vid", "is_primary").groupBy(one)).applyInArrow(pack, PACKED)


def _piece(number: int, **arrays: np.ndarray) -> pa.Table:
    return pa.table({"what": pa.array(list(arrays)), "piece": pa.array([number] * len(arrays), pa.int32()), "held": pa.array([x.tobytes() for x in arrays.values()], pa.binary())})


def is_held(graph: Graph) -> bool:
    return graph.edges.count() <= HELD and graph.vertices.count() <= 2 * HELD


def arcs_in_pieces(graph: Graph, centers: DataFrame, order: str) -> DataFrame:
    """The arrays of ``packed_arcs`` over all vertices of a graph, in pieces: numbers come from joins, no task sees all arcs.

    All but the kinds is made once for a graph and an order, whatever decomposition asks."""
    if order not in graph.held:
        size = max(1, -(-graph.vertices.count() // (2 * graph.edges.count() // PIECE + 1)))
        spots = materialize(global_index(graph.vertices, ["vid"], "spot").select("vid", "spot", F.expr(f"cast(spot div {size} as int)").alias("piece")), "spots")
        x, y = spots.select(F.col("vid").alias("a"), F.col("spot").alias("pa")), spots.select(F.col("vid").alias("b"), F.col("spot").alias("pb"))
        rank = (lambda c, p: F.col(p)) if order == "vid" else (lambda c, p: F.xxhash64(c))
        arc = lambda src, dst, far: F.struct(F.col(src).alias("src"), F.col(dst).alias("dst"), rank(far, dst).alias("rank"))
        arcs = graph.edges.select("a", "b").join(x, "a").join(y, "b").select(F.explode(F.array(arc("pa", "pb", "b"), arc("pb", "pa", "a"))).alias("arc")).select("arc.*", F.expr(f"cast(arc.src div {size} as int)").alias("piece"))

        def pack(left: pa.Table, right: pa.Table) -> pa.Table:
            src, dst = left.column("src").to_numpy(), left.column("dst").to_numpy()
            spot, number = right.column("spot").to_numpy(), right.column("piece")[0].as_py()
            near = dst[np.lexsort((dst, left.column("rank").to_numpy(), src))]
            many = np.bincount(src - number * size, minlength=len(spot))
            return _piece(number, names=right.column("vid").to_numpy()[np.argsort(spot)], many=many.astype(np.int32), near=near.astype(np.int32))

        graph.held[order] = spots, materialize(arcs.groupBy("piece").cogroup(spots.groupBy("piece")).applyInArrow(pack, PACKED), "arcs")
    spots, packed = graph.held[order]
    kind = F.coalesce(F.when(F.col("is_primary"), 2).otherwise(F.when(~F.col("is_primary"), 1)), F.lit(0))
    marked = spots.join(centers.select("vid", "is_primary"), "vid", "left").select("spot", "piece", kind.alias("kind"))

    def kinds(table: pa.Table) -> pa.Table:
        order_ = np.argsort(table.column("spot").to_numpy())
        return _piece(table.column("piece")[0].as_py(), kinds=table.column("kind").to_numpy()[order_].astype(np.int8))

    return packed.unionByName(materialize(marked.groupBy("piece").applyInArrow(kinds, PACKED), "arc-kinds"))


def _arrays(held: pa.Table) -> list[np.ndarray]:
    """names, starts, near and kinds from their pieces, copied once."""
    order = np.argsort(held.column("piece").to_numpy(), kind="stable")
    what, pieces, out = held.column("what").to_pylist(), [c for chunk in held.column("held").chunks for c in chunk], {}
    for name, kind in {"names": np.int64, "many": np.int32, "near": np.int32, "kinds": np.int8}.items():
        parts = [np.frombuffer(pieces[i].as_buffer(), kind) for i in order if what[i] == name]
        out[name] = parts[0] if len(parts) == 1 else np.concatenate(parts) if parts else np.zeros(0, kind)
    starts = np.zeros(len(out["many"]) + 1, np.int32)  # at most 2 * HELD arcs
    np.cumsum(out.pop("many"), out=starts[1:])
    return [out["names"], starts, out["near"], out["kinds"]]


def by_share(asked: DataFrame, arcs: DataFrame, shares: int, search, schema: str) -> DataFrame:
    """``search`` (questions (vid), arrays) in every task, for its share of the questions."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return search(np.unique(left.column("vid").to_numpy()), _arrays(right))

    every = arcs.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(shares - 1))))
    dealt = asked.select("vid", F.pmod(F.xxhash64("vid"), F.lit(shares)).cast("int").alias("share"))
    return dealt.groupBy("share").cogroup(every.groupBy("share")).applyInArrow(run, schema)


def among(held: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """Which of the asked numbers are held; these are in order."""
    return held[np.minimum(np.searchsorted(held, asked), len(held) - 1)] == asked if len(held) else np.zeros(len(asked), bool)


def _different(keys: np.ndarray) -> np.ndarray:
    keys = np.sort(keys)
    return keys[np.concatenate([[True], keys[1:] != keys[:-1]])] if len(keys) else keys


def _arcs_of(starts: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(which of ``at``, place of the arc) of all arcs of the vertices ``at``, in order."""
    many = (starts[at + 1] - starts[at]).astype(np.int64)
    row = np.repeat(np.arange(len(at)), many)
    return row, np.arange(len(row)) + np.repeat(starts[at] - np.cumsum(many) + many, many)


def centers_of(spots: np.ndarray, arrays: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place of the center, vertices visited, arcs looked at) of vertices by their places, by the rules of ``decompose.lookup_center``."""
    parts = [_centers_of(spots[i : i + CHUNK], arrays) for i in range(0, len(spots), CHUNK)] or [(np.zeros(0, np.int64),) * 3]
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _centers_of(spots: np.ndarray, arrays: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    names, starts, near, kinds = arrays
    n, many = len(names), len(spots)
    visited, looked, least, ended = np.ones(many, np.int64), np.zeros(many, np.int64), spots.copy(), np.full(many, -1)
    level, before = np.arange(many) * n + spots, np.zeros(0, np.int64)  # question and vertex in one number, in order
    levels, hits, sum_ = [], [], 0
    while len(level):
        own, v = np.divmod(level, n)
        hit = kinds[v] == 2
        ended[own[hit]] = len(levels)
        levels.append(level)
        hits.append(level[hit])
        going = ended[own] < 0
        own, v = own[going], v[going]
        degree = starts[v + 1] - starts[v]
        sum_ += int(degree.sum())
        if sum_ > MOST and many > 1:
            halves = [_centers_of(x, arrays) for x in (spots[: many // 2], spots[many // 2 :])]
            return tuple(np.concatenate(x) for x in zip(*halves, strict=True))
        looked += np.bincount(own, degree, many).astype(np.int64)
        row, arc = _arcs_of(starts, v)
        # neighbours of a level lie in it, in the one before or in the next one
        fresh = _different(own[row] * n + near[arc])
        fresh = fresh[~among(level, fresh)]
        level, before = fresh[~among(before, fresh)], level
        own, v = np.divmod(level, n)
        visited += np.bincount(own, minlength=many)
        first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]])) if len(own) else own
        least[own[first]] = np.minimum(least[own[first]], v[first])
    # what leads on to a primary of its question, level by level back from it
    leads = [np.zeros(0, np.int64)] * len(levels)
    for depth in range(len(levels) - 1, 0, -1):
        leads[depth] = _different(np.concatenate([leads[depth], hits[depth]]))
        own, v = np.divmod(leads[depth], n)
        row, arc = _arcs_of(starts, v)
        up = own[row] * n + near[arc]
        leads[depth - 1] = up[among(levels[depth - 1], up)]
    at = np.where(ended < 0, least, spots)
    for depth in range(len(levels) - 1):
        going = np.flatnonzero((ended > depth) & (kinds[at] == 0))
        row, arc = _arcs_of(starts, at[going])
        on = np.flatnonzero(among(leads[depth + 1], going[row] * n + near[arc]))  # by rank: the first that leads on is the least
        on = on[np.concatenate([[True], row[on][1:] != row[on][:-1]])] if len(on) else on
        at[going[row[on]]] = near[arc[on]]
    return at, visited, looked


def looked_up(asked: np.ndarray, arrays: list[np.ndarray]) -> pa.Table:
    """(vid, center, visited, looked) of asked vertices; one without arcs is a component of its own."""
    names = arrays[0]
    known = among(names, asked)
    center, visited, looked = asked.copy(), np.ones(len(asked), np.int64), np.zeros(len(asked), np.int64)
    at, visited[known], looked[known] = centers_of(np.searchsorted(names, asked[known]), arrays)
    center[known] = names[at]
    return pa.table({"vid": pa.array(asked), "center": pa.array(center), "visited": pa.array(visited), "looked": pa.array(looked)})


def met(asked: np.ndarray, arrays: list[np.ndarray]) -> pa.Table:
    """(center, vid, own, ops) of asked clusters: what a search outward from the center meets, with the center of each by its own look-up.

    The search goes on from members only; a vertex is looked up once a task, with its cost in the first row that has it."""
    names, starts, near, _ = arrays
    n, lone = len(names), asked[~among(names, asked)]
    spots = np.searchsorted(names, asked[among(names, asked)])
    own, cost = np.full(n, -1), np.zeros(n, np.int64)
    own[spots] = spots
    seen = front = spots * n + spots
    while len(front):
        c, v = np.divmod(front, n)
        row, arc = _arcs_of(starts, v)
        fresh = _different(c[row] * n + near[arc])
        fresh = fresh[~among(seen, fresh)]
        c, v = np.divmod(fresh, n)
        new = _different(v[own[v] < 0])
        own[new], visited, looked = centers_of(new, arrays)
        cost[new] = visited + looked
        seen, front = np.sort(np.concatenate([seen, fresh])), fresh[own[v] == c]
    c, v = np.divmod(seen, n)
    first = np.zeros(len(v), bool)
    first[np.unique(v, return_index=True)[1]] = True
    none = np.zeros(len(lone), np.int64)
    return pa.table({"center": pa.array(np.concatenate([names[c], lone])), "vid": pa.array(np.concatenate([names[v], lone])), "own": pa.array(np.concatenate([names[own[v]], lone])),
                     "ops": pa.array(np.concatenate([np.where(first, cost[v], 0), none]))})
