"""Exact inner-product top-k by the threshold algorithm over sorted per-dimension lists.

Vectors become integers, floor(scale * x), and rows are dealt into blocks by a hash of the
id.  A block has one sorted list a dimension.  A query walks all lists of a block side by
side, each from the end that its weight favours, looks up every row that it meets for the
first time, and stops when the sum of the current entries, which is the most that an unseen
row can reach, is below the k-th best score so far.  The k-th score is carried over blocks:
every query first walks the block of its own row, and enters all others with the score that
it found there.  A last step merges the blocks.

Rows are moved once and never copied; a block's rows come first, then the queries stream
past its lists.  Sums are exact: float64 below 2**53, 64-bit integers below 2**63, whole
numbers of any size beyond.

Defined results: vectors that are null, empty, or hold null or non-finite components take no
part; only vectors of equal length meet; a query never meets rows of its own id; repeated ids
are ranked as separate rows, and a repeated query id is asked once, with the vector that sorts
first; fewer than k rows give fewer results; a scaled component beyond 64 bits counts as the
nearest 64-bit number, and a score beyond 64 bits is ranked exactly and reported as null;
other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_batches, load, materialize
from .textbytes import releasing

K, SCALE = 10, 1024
ROW_BLOCK = 16384
WIDE = 1 << 140  # above every sum of products of 64-bit numbers


def quantised(vectors: DataFrame, scale: int = SCALE) -> DataFrame:
    """(vec_id, v array<bigint>) of the well-formed rows."""
    wide = vectors.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x")).filter("vec_id is not null and x is not null and size(x) > 0")
    finite = F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return wide.filter(finite).select("vec_id", F.transform("x", lambda v: F.floor(v * scale)).alias("v"))


class SortedLists:
    """The rows of one block (whole numbers as int64) and a list of them, ascending, for each dimension."""

    def __init__(self, rows: np.ndarray, ids: np.ndarray):
        by_id = np.argsort(ids, kind="stable")
        self.rows, self.ids = rows[by_id], ids[by_id]
        self.order = np.argsort(self.rows, axis=0, kind="stable").astype(np.int32)
        self.most = max(abs(int(rows.min(initial=0))), abs(int(rows.max(initial=0))))
        self._as: dict = {}

    def typed(self, query: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(rows, lists, query) in the narrowest type whose sums of products are exact."""
        bound = self.most * max(abs(int(query.min(initial=0))), abs(int(query.max(initial=0)))) * len(query)
        kind = np.float64 if bound < 2**53 else np.int64 if bound < 2**63 else object
        if kind not in self._as:
            rows = self.rows.astype(kind)
            self._as[kind] = rows, np.take_along_axis(rows, self.order, 0)
        return *self._as[kind], query.astype(kind)

    def best(self, query: np.ndarray, own: int, k: int, floor: int | None = None, step: int = 64) -> tuple[np.ndarray, np.ndarray, int, bool]:
        """(ids, scores, depth, stopped by the bound) of the k best rows, ties to smaller ids.

        ``floor`` is a score that k rows elsewhere reach: rows below it may be left out."""
        rows, lists, q = self.typed(query)
        n = len(rows)
        live = np.flatnonzero(query)
        positive = query[live] > 0
        seen = np.zeros(n, bool)
        best_s, best_i = np.zeros(0, rows.dtype), np.zeros(0, np.int64)
        depth, stopped = 0, False
        while depth < n and not stopped:
            upto = min(n, depth + max(step, depth // 4)) if len(live) else n
            if len(live):
                span = np.arange(depth, upto)
                at = np.where(positive[None, :], n - 1 - span[:, None], span[:, None])
                mask = np.zeros(n, bool)
                mask[self.order[at, live[None, :]].ravel()] = True
                fresh = np.flatnonzero(mask & ~seen)
            else:
                fresh = np.arange(n)  # a query of zeros: every score is 0
            seen[fresh] = True
            depth = upto
            if len(fresh):
                ok = self.ids[fresh] != own
                best_s, best_i = np.concatenate([best_s, rows[fresh][ok] @ q]), np.concatenate([best_i, self.ids[fresh][ok]])
                top = np.lexsort((best_i, -best_s))[:k]
                best_s, best_i = best_s[top], best_i[top]
            if depth < n:
                edge = lists[np.where(positive, n - depth, depth - 1), live] @ q[live]
                known = best_s[-1] if len(best_s) == k else None
                stopped = bool((known is not None and edge < known) or (floor is not None and edge < floor))
        return best_i, best_s, depth, stopped


FOUND = "query_id long, vec_id long, band int, score long, wide string, row_part int, depth int, rows int, stopped boolean"


def _walked(stream: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    """For batches sorted by (row_part, role): the rows of a part become lists, its queries walk them."""
    part, waiting, lists = None, [], None
    for batch in stream:
        parts, roles = batch.column("row_part").to_numpy(), batch.column("role").to_numpy()
        edges = np.flatnonzero(np.concatenate([[True], (parts[1:] != parts[:-1]) | (roles[1:] != roles[:-1])])) if len(parts) else []
        for a, z in zip(edges, [*edges[1:], len(parts)], strict=True):
            if parts[a] != part:
                part, waiting, lists = parts[a], [], None
            piece = batch.slice(a, z - a)
            if roles[a] == 0:
                waiting.append(piece)
                continue
            if lists is None:
                lists = {}
                ids, flat, bounds = _vectors(waiting)
                widths = np.diff(bounds)
                for width in np.unique(widths):
                    at = np.flatnonzero(widths == width)
                    lists[int(width)] = SortedLists(flat[bounds[at][:, None] + np.arange(width)], ids[at])
                waiting = []
            out = {c.split()[0]: [] for c in FOUND.split(", ")}
            ids, flat, bounds = _vectors([piece])
            for me, i, j, floor in zip(ids.tolist(), bounds, bounds[1:], piece.column("floor").to_pylist(), strict=False):
                if j - i in lists:
                    found, scores, depth, stopped = lists[int(j - i)].best(flat[i:j], me, k, floor)
                    scores = [int(x) for x in scores]
                    bands = [0 if -(2**63) <= x < 2**63 else 1 if x > 0 else -1 for x in scores]
                    out["vec_id"] += found.tolist()
                    out["band"] += bands
                    out["score"] += [x if b == 0 else None for x, b in zip(scores, bands, strict=True)]
                    out["wide"] += [None if b == 0 else f"{WIDE + x:043d}" for x, b in zip(scores, bands, strict=True)]
                    for name, value in (("query_id", me), ("row_part", int(part)), ("depth", depth), ("rows", len(lists[int(j - i)].ids)), ("stopped", stopped)):
                        out[name] += [value] * len(scores)
            kinds = {"band": pa.int32(), "wide": pa.string(), "row_part": pa.int32(), "depth": pa.int32(), "rows": pa.int32(), "stopped": pa.bool_()}
            yield pa.RecordBatch.from_arrays([pa.array(v, kinds.get(c, pa.int64())) for c, v in out.items()], names=list(out))


def _vectors(batches: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, flat components, bounds) of the vectors of some batches."""
    if not batches:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(1, np.int64)
    columns = [b.column("v") for b in batches]
    flat = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in columns])
    sizes = np.concatenate([c.value_lengths().to_numpy(zero_copy_only=False) for c in columns])
    return np.concatenate([b.column("vec_id").to_numpy() for b in batches]), flat, np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)


def walks(vectors: DataFrame, is_query, *, k: int = K, scale: int = SCALE, row_block: int = ROW_BLOCK) -> DataFrame:
    """What every walk found: query_id, vec_id, score and its band, with the depth, the rows of the block and whether the bound ended the walk.

    A walk that finds nothing above its carried score leaves no rows."""
    ready = materialize(quantised(vectors, scale), "vectors")
    blocks = max(1, -(-ready.count() // row_block))
    part = F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)).cast("int")
    rows = ready.select(part.alias("row_part"), F.lit(0).alias("role"), "vec_id", "v", F.lit(None).cast("bigint").alias("floor"))
    asked = ready.filter(is_query).groupBy("vec_id").agg(F.min("v").alias("v")).withColumn("home", part)

    def run(queries: DataFrame) -> DataFrame:
        dealt = rows.unionByName(queries.select("row_part", F.lit(1).alias("role"), "vec_id", "v", "floor")).repartition("row_part").sortWithinPartitions("row_part", "role")
        return dealt.mapInArrow(releasing(lambda stream: _walked(stream, k)), FOUND)

    with arrow_batches(vectors.sparkSession, 2048):
        home = materialize(run(asked.select(F.col("home").alias("row_part"), "vec_id", "v", F.lit(None).cast("bigint").alias("floor"))), "walks-home")
        if blocks == 1:
            return home
        # a score that k rows reach; scores beyond 64 bits carry nothing
        floors = home.filter("band = 0").groupBy("query_id").agg(F.min("score").alias("floor"), F.count(F.lit(1)).alias("n")).filter(F.col("n") == k).select(F.col("query_id").alias("vec_id"), "floor")
        away = asked.join(floors, "vec_id", "left").withColumn("row_part", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).filter("row_part <> home")
        return home.unionByName(materialize(run(away), "walks-away"))


def top_k(vectors: DataFrame, is_query, *, k: int = K, **options) -> DataFrame:
    """query_id, rank, vec_id, score: the k best other rows of every row for which ``is_query`` holds."""
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("band"), F.desc("score"), F.desc("wide"), "vec_id"))
    return walks(vectors, is_query, k=k, **options).withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op3_topk(spark, sf_dir):
    return top_k(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 100 == 0)


SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: cast(floor(1024 * cast(x as double)) as bigint)) as q
  from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(cast(x as double)))) = 0),
s as (
  select a.vec_id as query_id, b.vec_id as vec_id,
         cast(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) as bigint) as score
  from v a join v b on a.vec_id % 100 = 0 and a.vec_id <> b.vec_id),
r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank from s)
select query_id, rank, vec_id, score from r where rank <= 10
"""

QUERIES = {"op3_topk": op3_topk}
ORACLES = {"op3_topk": SQL}
