"""Similarity join on word shingles under several global token orders.

Two documents link when their shingle sets have a Jaccard similarity of at least
``percent`` per cent; components of the links are reported.

1. Documents with equal sets are one class; its least id stands for it from then on.
2. Document frequencies over all classes split the tokens of the lower half of the hash
   range into rare and frequent ones.  Every global order starts with the rare tokens
   and ends with the frequent ones; within these the orders differ by hash.
3. Linked sets share a token in their prefixes under every order.  The prefixes of the
   first order are indexed.  A token with few documents yields all its pairs; one with
   many yields pairs with a few hubs.  Tokens lie in buckets; a bucket of more than
   ``bucket_tokens`` entries is taken apart: its long postings never come together in one
   task, the others are dealt anew.
4. Pairs pass the other orders' prefix intersections and a bound on the symmetric
   difference from parity bitmaps, then are verified on the whole sets.
5. Components.  Documents of a long posting that are not yet connected are then paired
   across components, filtered and verified alike, so that no link between different
   texts is lost; pairs inside a component cannot change it.

Defined results: null or wordless texts have an empty set and link with nothing; a null
doc_id takes no part and has a null component; rows with equal ids are one vertex;
other columns are ignored; an empty table gives an empty result.  ``keep_one`` tells rows
apart by id and text: different texts of one id, or of no id, are vertices of their own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.contraction import contract_components
from ..operators.trees import global_index
from .common import arrow_batches, discard, load, materialize, shuffle_width
from .packed import COUNT_SCHEMA, bucket_of, contains, count_rows, frequent_keys, merged_keys, mix64, pack48, unpack48
from .textbytes import byte_view, concat_column, release, releasing, slices

FREQUENT = 16  # documents from which on a token is frequent; also the longest posting of which all pairs are taken
HUBS = 3
NEAR_ROUNDS = 2
ORDERS = 3
PART_BYTES = 4 << 20
SLICE = 1 << 19
BUCKET_TOKENS = 2_000_000
BLOCK_ROWS, BLOCK_BYTES = 10_000, 16 << 20
CHUNK = 1 << 16

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_TABLE = np.random.default_rng(20240607).integers(0, 2**64, 256, dtype=np.uint64)
_BASE = 0x5851F42D4C957F2D
_STEPS = np.random.default_rng(77).integers(0, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if "up" not in _POWERS or len(_POWERS["up"]) < n:
        size = max(n, SLICE + (1 << 18))
        for name, base in (("up", _BASE), ("down", pow(_BASE, -1, 1 << 64))):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _POWERS[name] = np.cumprod(steps, dtype=np.uint64)
    return _POWERS["up"], _POWERS["down"]


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, words before each document): words are runs of bytes that are not ASCII white space."""
    solid = ~_SPACE[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    heads = offsets[:-1][offsets[:-1] < len(data)]
    first[heads] = solid[heads]
    last = solid.copy()
    last[:-1] &= ~solid[1:]
    tails = offsets[1:] - 1
    tails = tails[tails >= 0]
    last[tails] = solid[tails]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    up, down = _powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_TABLE[_LOWER[data]] * up[: len(data)], out=total[1:])
    hashed = mix64((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))
    return hashed, np.searchsorted(starts, offsets)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, words: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text."""
    w, at = word_hashes(data, offsets)
    total = np.zeros(max(0, len(w) - words + 1), np.uint64)
    for k in range(words):
        total += w[k : k + len(total)] * _STEPS[k]
    h = mix64(total)
    out = []
    for a, b in zip(at, at[1:], strict=False):
        if b - a >= words:
            out.append(np.unique(h[a : b - words + 1]))
        elif b > a:
            short = (w[a:b] * _STEPS[: b - a]).sum(dtype=np.uint64, keepdims=True) + _STEPS[63 - (b - a)]
            out.append(mix64(short))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def table_sets(column: pa.Array, words: int) -> Iterator[np.ndarray]:
    data, offsets = byte_view(column)
    i, rows = 0, len(offsets) - 1
    while i < rows:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE, "right")) - 1)
        yield from shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], words)
        i = j


def described(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, n_shingles, hi, lo): size and 128-bit digest of every set."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, "text", SLICE):
                sets = list(table_sets(part.column("text"), words))
                hi = [mix64(s).sum(dtype=np.uint64).astype(np.int64) for s in sets]
                lo = [mix64(s ^ _STEPS[0]).sum(dtype=np.uint64).astype(np.int64) for s in sets]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(hi, pa.int64()), pa.array(lo, pa.int64())], names=["doc_id", "n_shingles", "hi", "lo"])

    return docs.mapInArrow(releasing(run), "doc_id long, n_shingles long, hi long, lo long")


# --- orders, prefixes, sketches ------------------------------------------------------------

_HALF = np.uint64(1 << 63)


def token_rank(h: np.ndarray, frequent: np.ndarray) -> np.ndarray:
    """0 for rare, 1 for uncounted, 2 for frequent tokens."""
    return np.where(h >= _HALF, 1, np.where(contains(frequent, h >> np.uint64(16)), 2, 0))


def order_hash(h: np.ndarray, order: int) -> np.ndarray:
    return h if order == 0 else mix64(h ^ _STEPS[10 + order])


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def prefixes(h: np.ndarray, frequent: np.ndarray, percent: int, orders: int = ORDERS) -> list[np.ndarray]:
    """The prefix of a set under each order (first order: hashes; others: 32-bit marks, sorted)."""
    rank, p, out = token_rank(h, frequent), prefix_length(len(h), percent), []
    for k in range(orders):
        by = order_hash(h, k)
        chosen = np.lexsort((by, rank))[:p] if rank.any() else np.argpartition(by, p - 1)[:p]
        out.append(h[chosen] if k == 0 else np.unique((by[chosen] >> np.uint64(16)).astype(np.uint32)))
    return out


def parity_bits(h: np.ndarray) -> np.ndarray:
    """Parity of the number of tokens in each of at least twice as many cells, packed."""
    cells = 1 << max(6, (2 * len(h) - 1).bit_length())
    bits = np.bincount((mix64(h ^ _STEPS[9]) & np.uint64(cells - 1)).astype(np.int64), minlength=cells) & 1
    return np.packbits(bits.astype(np.uint8), bitorder="little")


def least_difference(a: np.ndarray, b: np.ndarray) -> int:
    """A lower bound on the size of the symmetric difference."""
    if len(a) < len(b):
        a, b = b, a
    while len(a) > len(b):
        a = a[: len(a) // 2] ^ a[len(a) // 2 :]
    return int(np.bitwise_count(a ^ b).sum())


def needed(na: int, nb: int, percent: int) -> int:
    """The least intersection that links sets of these sizes."""
    return -(-percent * (na + nb) // (100 + percent))


def meet(a: np.ndarray, b: np.ndarray) -> bool:
    return bool(contains(b, a).any()) if len(a) <= len(b) else bool(contains(a, b).any())


SKETCH_SCHEMA = "bucket int, entries long, ids binary, sizes binary, counts binary, tokens binary, sketch_id long, n long, parity binary, marks array<binary>"
INDEX_COLUMNS = ("ids", "sizes", "counts", "tokens")


def _index(table: pa.Table, frequent: np.ndarray, words: int, percent: int, buckets: int) -> pa.Table:
    """Index rows of the first order by bucket, and one sketch row a document."""
    ids = table.column("doc_id").to_numpy()
    first, sketches = [], []
    for i, h in zip(ids, table_sets(concat_column(table, "text"), words), strict=True):
        p = prefixes(h, frequent, percent)
        first.append(p[0] >> np.uint64(16))
        sketches.append((int(i), len(h), parity_bits(h).tobytes(), [m.tobytes() for m in p[1:]]))
    sizes = np.array([s[1] for s in sketches], np.int64)
    row = np.repeat(np.arange(len(first)), [len(f) for f in first])
    keys = np.concatenate([np.zeros(0, np.uint64), *first])
    place = bucket_of(keys, buckets)
    order = np.argsort(place, kind="stable")
    place, row, keys = place[order], row[order], keys[order]
    edges = np.searchsorted(place, np.arange(buckets + 1))
    rows = []
    for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)):
        if j > i:
            docs, counts = np.unique(row[i:j], return_counts=True)  # rows ascend within a bucket
            rows.append((b, int(j - i), ids[docs].astype("<i8").tobytes(), sizes[docs].astype("<i4").tobytes(), counts.astype("<u4").tobytes(), pack48(keys[i:j])))
    none = [None] * len(rows)
    nothing = [None] * len(sketches)
    cols = list(zip(*rows, strict=True)) or [()] * 6
    sk = list(zip(*sketches, strict=True)) or [()] * 4
    data = [[*cols[0], *nothing], *([*c, *nothing] for c in cols[1:]), *([*none, *s] for s in sk)]
    kinds = [pa.int32(), pa.int64(), *[pa.binary()] * 4, pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.binary())]
    names = ["bucket", "entries", *INDEX_COLUMNS, "sketch_id", "n", "parity", "marks"]
    return pa.table([pa.array(d, k) for d, k in zip(data, kinds, strict=True)], names=names)


PAIR_SCHEMA = "a long, b long, key long, members binary"


def _fits(na: np.ndarray, nb: np.ndarray, percent: int) -> np.ndarray:
    return 100 * np.minimum(na, nb) >= percent * np.maximum(na, nb)


def _unpacked(cols: dict) -> tuple[np.ndarray, ...]:
    """(ids, sizes, keys, row of each key) of packed index rows."""
    ids, sizes = np.frombuffer(b"".join(cols["ids"]), "<i8"), np.frombuffer(b"".join(cols["sizes"]), "<i4").astype(np.int64)
    counts = np.frombuffer(b"".join(cols["counts"]), "<u4").astype(np.int64)
    keys = np.concatenate([unpack48(x) for x in cols["tokens"]])
    return ids, sizes, keys, np.repeat(np.arange(len(ids)), counts)


def _pairs(table: pa.Table, percent: int) -> pa.Table:
    """Pairs of documents that share an indexed token, and the members of long postings."""
    return _met(*_unpacked({k: table.column(k).to_pylist() for k in INDEX_COLUMNS}), percent)


def _met(ids: np.ndarray, sizes: np.ndarray, keys: np.ndarray, row: np.ndarray, percent: int) -> pa.Table:
    order = np.lexsort((ids[row], keys))
    k, r = keys[order], row[order]
    same = (k[1:] == k[:-1]) & (ids[r][1:] == ids[r][:-1])
    if same.any():  # repeated rows
        keep = np.concatenate([[True], ~same])
        k, r = k[keep], r[keep]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    size = np.diff(np.append(first, len(k)))
    pa_, pb_, long_keys, long_members = [], [], [], []
    for m in np.unique(size):
        at = first[size == m]
        if m < 2:
            continue
        members = r[at[:, None] + np.arange(m)]
        if m <= FREQUENT:
            i, j = np.triu_indices(m, 1)
            pa_.append(members[:, i].ravel())
            pb_.append(members[:, j].ravel())
        else:
            for key, posting in zip(k[at], members, strict=True):
                long_keys.append(int(key))
                long_members.append(posting)
    if long_members:
        # a hub should resemble many: the members met most often in this bucket's long postings, and some by hash
        often = np.bincount(np.concatenate(long_members), minlength=len(ids))
        noise = mix64(ids.astype(np.uint64))
        for posting in long_members:
            hubs = {int(posting[np.lexsort((ids[posting], -often[posting]))[0]])}
            hubs.update(int(x) for x in posting[np.argsort(noise[posting], kind="stable")[: HUBS - 1]])
            for hub in hubs:
                pa_.append(np.full(len(posting), hub))
                pb_.append(posting)
    a, b = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (pa_, pb_))
    good = (a != b) & _fits(sizes[a], sizes[b], percent)
    both = np.unique(np.sort(np.stack([ids[a[good]], ids[b[good]]], 1), axis=1), axis=0) if good.any() else np.zeros((0, 2), np.int64)
    n, m = len(both), len(long_keys)
    return pa.table({
        "a": pa.array([*both[:, 0], *[None] * m], pa.int64()), "b": pa.array([*both[:, 1], *[None] * m], pa.int64()), "key": pa.array([*[None] * n, *long_keys], pa.int64()),
        "members": pa.array([*[None] * n, *(np.stack([ids[p], sizes[p]], 1).astype("<i8").tobytes() for p in long_members)], pa.binary())})


def taken_apart(index: DataFrame, hot: DataFrame, percent: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(pairs, long postings (key, vid, n), table to discard) of oversized buckets, hot(bucket, splits).

    Numbers of documents are added up on the map side, so that only postings of at most
    FREQUENT members are gathered by key; the others stay rows and meet a few hubs, the members
    that come first under some hashes."""

    def unpack(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                one = batch.slice(i, 1)
                ids, sizes, keys, row = _unpacked({k: one.column(k).to_pylist() for k in INDEX_COLUMNS})
                bucket, splits = one.column("bucket")[0].as_py(), one.column("splits")[0].as_py()
                for a in range(0, len(keys), CHUNK):
                    k, r = keys[a : a + CHUNK], row[a : a + CHUNK]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), bucket, np.int32)), pa.array((mix64(k) % np.uint64(splits)).astype(np.int32)), pa.array(k.astype(np.int64)), pa.array(ids[r]), pa.array(sizes[r])], names=["bucket", "split", "key", "vid", "n"])

    def pair(table: pa.Table) -> pa.Table:
        ids, first, row = np.unique(table.column("vid").to_numpy(), return_index=True, return_inverse=True)
        out = _met(ids, table.column("n").to_numpy()[first], table.column("key").to_numpy().astype(np.uint64), row, percent)
        release()
        return out.select(["a", "b"])

    wide = index.join(hot, "bucket").select("bucket", "splits", *INDEX_COLUMNS)
    rows = materialize(wide.mapInArrow(releasing(unpack), "bucket int, split int, key long, vid long, n long").distinct(), "near-hot")
    firsts = [F.min_by(F.struct("vid", "n"), F.xxhash64("vid", F.lit(h))).alias(f"h{h}") for h in range(HUBS)]
    long = rows.groupBy("key").agg(F.count(F.lit(1)).alias("m"), *firsts).filter(F.col("m") > FREQUENT)
    members = rows.join(long.select("key"), "key", "left_semi").select("key", "vid", "n")
    hubs = long.select("key", F.explode(F.array_distinct(F.array(*[f"h{h}" for h in range(HUBS)]))).alias("hub"))
    fits = 100 * F.least("n", "hub.n") >= percent * F.greatest("n", "hub.n")
    near = members.join(hubs, "key").filter((F.col("vid") != F.col("hub.vid")) & fits).select(F.least("vid", "hub.vid").alias("a"), F.greatest("vid", "hub.vid").alias("b"))
    few = rows.join(long.select("key"), "key", "left_anti").groupBy("bucket", "split").applyInArrow(pair, "a long, b long")
    return near.unionByName(few), members, rows


def filtered(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that meet under every order and may be similar enough by their parity bitmaps."""

    def run(batches):
        for batch in batches:
            na, nb = batch.column("na").to_pylist(), batch.column("nb").to_pylist()
            cols = [batch.column(c).to_pylist() for c in ("pa", "pb", "ma", "mb")]
            good = []
            for x, y, p, q, ma, mb in zip(na, nb, *cols, strict=True):
                room = x + y - 2 * needed(x, y, percent)
                ok = least_difference(np.frombuffer(p, np.uint8), np.frombuffer(q, np.uint8)) <= room
                good.append(ok and all(meet(np.frombuffer(u, np.uint32), np.frombuffer(v, np.uint32)) for u, v in zip(ma, mb, strict=True)))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    left = sketches.select(F.col("sketch_id").alias("a"), F.col("n").alias("na"), F.col("parity").alias("pa"), F.col("marks").alias("ma"))
    right = sketches.select(F.col("sketch_id").alias("b"), F.col("n").alias("nb"), F.col("parity").alias("pb"), F.col("marks").alias("mb"))
    return pairs.join(left, "a").join(right, "b").mapInArrow(releasing(run), "a long, b long")


def verified(pairs: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """The pairs whose whole sets are similar enough."""

    def sets(batches):
        for batch in batches:
            for part in slices(batch, "text", SLICE):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([s.tobytes() for s in table_sets(part.column("text"), words)], pa.binary())], names=["doc_id", "tokens"])

    def run(batches):
        for batch in batches:
            good = []
            for x, y in zip(batch.column("sa"), batch.column("sb"), strict=True):
                u, v = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = len(np.intersect1d(u, v, assume_unique=True))
                good.append(100 * both >= percent * (len(u) + len(v) - both))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    wanted = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    held = materialize(texts.join(wanted, "doc_id", "left_semi").mapInArrow(releasing(sets), "doc_id long, tokens binary"), "near-sets")
    left, right = held.select(F.col("doc_id").alias("a"), F.col("tokens").alias("sa")), held.select(F.col("doc_id").alias("b"), F.col("tokens").alias("sb"))
    out = materialize(pairs.join(left, "a").join(right, "b").mapInArrow(releasing(run), "a long, b long"), "near-links")
    discard(held)
    return out


def folded(bits: np.ndarray, size: int) -> np.ndarray:
    """Rows of parity bitmaps folded down to ``size`` bytes."""
    while bits.shape[1] > size:
        half = bits.shape[1] // 2
        bits = bits[:, :half] ^ bits[:, half:]
    return bits


def _best(u: np.ndarray, w: np.ndarray, d: np.ndarray, vr: np.ndarray, best: int) -> tuple[np.ndarray, ...]:
    """The ``best`` nearest right rows of every left row."""
    order = np.lexsort((vr[w], d, u))
    u, w, d = u[order], w[order], d[order]
    first = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])[: len(u)])
    keep = np.arange(len(u)) - np.repeat(first, np.diff(np.append(first, len(u)))) < best
    return u[keep], w[keep], d[keep]


def nearest(left: pa.Table, right: pa.Table, percent: int, best: int | None, block: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row of left, row of right) of pairs in different components that the parity bound admits, a bounded
    number at a time; at most ``best`` a left row."""
    nl, nr = left.column("n").to_numpy(), right.column("n").to_numpy()
    cl, cr = left.column("comp").to_numpy(), right.column("comp").to_numpy()
    vl, vr = left.column("vid").to_numpy(), right.column("vid").to_numpy()
    pl, pr = left.column("parity").to_pylist(), right.column("parity").to_pylist()
    sl, sr = np.array([len(x) for x in pl]), np.array([len(x) for x in pr])
    held = (np.zeros(0, np.int64),) * 3
    for a in np.unique(sl):
        for b in np.unique(sr):
            i, j, size = np.flatnonzero(sl == a), np.flatnonzero(sr == b), int(min(a, b))
            x = folded(np.frombuffer(b"".join(pl[k] for k in i), np.uint8).reshape(-1, a), size).view(np.uint64)
            y = folded(np.frombuffer(b"".join(pr[k] for k in j), np.uint8).reshape(-1, b), size).view(np.uint64)
            for k in range(0, len(i), step := max(1, block // max(1, y.size))):
                r = i[k : k + step]
                d = np.bitwise_count(x[k : k + step, None, :] ^ y[None, :, :]).sum(2, dtype=np.int64)
                both = nl[r][:, None] + nr[j][None, :]
                ok = (cl[r][:, None] != cr[j][None, :]) & (vl[r][:, None] != vr[j][None, :]) & _fits(nl[r][:, None], nr[j][None, :], percent) & (d <= both - 2 * -(-percent * both // (100 + percent)))
                u, w = np.nonzero(ok)
                if best is None:
                    for c in range(0, len(u), CHUNK):
                        yield r[u[c : c + CHUNK]], j[w[c : c + CHUNK]]
                elif len(u):
                    held = _best(*(np.concatenate(p) for p in zip(held, (r[u], j[w], d[u, w]), strict=True)), vr, best)
    if len(held[0]):
        yield held[0], held[1]


def posting_members(postings: DataFrame) -> DataFrame:
    """(key, vid, n) of long postings."""

    def split(batches):
        for batch in batches:
            for key, blob in zip(batch.column("key").to_pylist(), batch.column("members").to_pylist(), strict=True):
                m = np.frombuffer(blob, "<i8").reshape(-1, 2)
                for i in range(0, len(m), CHUNK):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(m[i : i + CHUNK]), key)), pa.array(m[i : i + CHUNK, 0]), pa.array(m[i : i + CHUNK, 1])], names=["key", "vid", "n"])

    return postings.select("key", "members").mapInArrow(releasing(split), "key long, vid long, n long")


def across(members: DataFrame, sketches: DataFrame, comp: DataFrame, percent: int, best: int | None, block_rows: int = BLOCK_ROWS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Pairs within long postings whose ends are not connected yet and pass the parity bound.

    Members outside a posting's largest component meet all its members, block by block on
    both sides; a block is bounded in rows and in bytes of its bitmaps.  ``best`` keeps the
    nearest few of each member in each block, None all."""
    now = members.join(comp, "vid", "left").withColumn("comp", F.coalesce("comp", "vid"))
    now = materialize(now, "near-members")
    shares = now.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("share"), F.sum("n").alias("tokens"))
    keys = shares.groupBy("key").agg(F.max_by("comp", F.struct("share", "comp")).alias("top"), F.sum("share").alias("m"), F.sum("tokens").alias("tokens"),
                                     (F.sum("share") - F.max("share")).alias("rest"), (F.sum("tokens") - F.max_by("tokens", F.struct("share", "comp"))).alias("rest_tokens"), F.count(F.lit(1)).alias("comps")).filter("comps > 1")
    # a bitmap has at most four bits a token, or eight bytes
    blocks = lambda m, tokens: F.ceil(F.greatest(F.col(m) / block_rows, (F.col(tokens) / 2 + 8 * F.col(m)) / block_bytes)).cast("int")
    open_ = now.join(keys.select("key", "top", blocks("m", "tokens").alias("all_blocks"), blocks("rest", "rest_tokens").alias("rest_blocks")), "key")
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    own = open_.select("key", F.pmod(F.xxhash64("vid"), F.col("all_blocks")).cast("int").alias("block"), spread("rest_blocks").alias("side"), F.lit(0).alias("role"), "vid", "n", "comp")
    others = open_.filter("comp <> top").select("key", spread("all_blocks").alias("block"), F.pmod(F.xxhash64("vid"), F.col("rest_blocks")).cast("int").alias("side"), F.lit(1).alias("role"), "vid", "n", "comp")
    marks = sketches.select(F.col("sketch_id").alias("vid"), "parity")

    def meet_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        left, right = table.filter(pc.equal(table.column("role"), 1)), table.filter(pc.equal(table.column("role"), 0))
        if left.num_rows and right.num_rows:
            vl, vr = left.column("vid").to_numpy(), right.column("vid").to_numpy()
            for u, w in nearest(left, right, percent, best):
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(vl[u], vr[w])), pa.array(np.maximum(vl[u], vr[w]))], names=["a", "b"])
        release()

    rows = own.unionByName(others).join(marks, "vid")
    met = materialize(rows.groupBy("key", "block", "side").applyInArrow(meet_all, "a long, b long").distinct(), "near-across")
    discard(now)
    return met


def components(docs: DataFrame, *, words: int = 4, percent: int = 85, part_bytes: int = PART_BYTES, bucket_tokens: int = BUCKET_TOKENS) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    return _named(*_classes_and_components(docs, words, percent, part_bytes, bucket_tokens))


def _named(told: DataFrame, comp: DataFrame) -> DataFrame:
    named = told.join(comp.select(F.col("vid").alias("class_id"), "comp"), "class_id", "left")
    return named.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "class_id", "doc_id")).alias("component_id"))


def _classes_and_components(docs: DataFrame, words: int, percent: int, part_bytes: int, bucket_tokens: int) -> tuple[DataFrame, DataFrame]:
    """((doc_id, n_shingles, class_id) of every row, (vid, comp) of classes that link)."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    with arrow_batches(spark, 2000):
        seen = materialize(described(rows, words), "near-digests")
    groups = seen.filter("doc_id is not null and n_shingles > 0").groupBy("hi", "lo").agg(F.min("doc_id").alias("class_id"), F.first("n_shingles").alias("n_shingles"))
    told = materialize(seen.join(groups, ["hi", "lo", "n_shingles"], "left"), "near-classes")
    discard(seen)
    total = rows.agg(F.sum(F.octet_length("text"))).head()[0] or 0
    parts = max(shuffle_width(spark), -(-total // part_bytes))
    classes = told.filter("doc_id = class_id").select("doc_id").distinct()
    texts = rows.join(classes, "doc_id", "left_semi")
    grouped = texts.withColumn("part", F.pmod("doc_id", F.lit(parts)).cast("int")).groupBy("part")

    def count(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        out = count_rows(key[0].as_py(), [s[s < _HALF] >> np.uint64(16) for s in table_sets(concat_column(table, "text"), words)], 2 * parts)
        release()
        return out

    def index(left: pa.Table, right: pa.Table) -> pa.Table:
        out = _index(left, merged_keys(right), words, percent, parts)
        release()
        return out

    def pair(table: pa.Table) -> pa.Table:
        out = _pairs(table, percent)
        release()
        return out

    frequent = frequent_keys(grouped.applyInArrow(count, COUNT_SCHEMA), FREQUENT + 1)
    indexed = materialize(grouped.cogroup(frequent.groupBy("part")).applyInArrow(index, SKETCH_SCHEMA), "near-index")
    sketches = indexed.filter("sketch_id is not null").select("sketch_id", "n", "parity", "marks")
    buckets = indexed.filter("bucket is not null").select("bucket", "entries", *INDEX_COLUMNS)
    hot = materialize(buckets.groupBy("bucket").agg(F.sum("entries").alias("entries")).filter(F.col("entries") > bucket_tokens)
                      .select("bucket", F.ceil(2 * F.col("entries") / bucket_tokens).cast("int").alias("splits")), "near-hot-buckets")
    any_hot = not hot.isEmpty()
    cool = buckets.join(hot, "bucket", "left_anti") if any_hot else buckets
    met = materialize(cool.groupBy("bucket").applyInArrow(pair, PAIR_SCHEMA), "near-pairs")
    pairs, postings = met.filter("a is not null").select("a", "b"), met.filter("members is not null").select("key", "members")
    members, apart = posting_members(postings), None
    if any_hot:
        more_pairs, more_members, apart = taken_apart(buckets, hot, percent)
        pairs, members = pairs.unionByName(more_pairs), members.unionByName(more_members)
    links = _links(pairs.distinct(), sketches, texts, words, percent)
    comp = materialize(contract_components(links), "near-components")
    members = materialize(members, "near-postings")
    discard(met, apart, hot)
    if not members.isEmpty():
        # nearest partners first, as long as they connect something; then all that the bound admits
        for best in (*[2] * NEAR_ROUNDS, None):
            more = across(members, sketches, comp, percent, best)
            found = None if more.isEmpty() else _links(more, sketches, texts, words, percent)
            discard(more)
            if found is not None and not found.isEmpty():
                links = links.unionByName(found)
                discard(comp)
                comp = materialize(contract_components(links), "near-components")
            elif found is None:
                break  # no pair is left that could link
    discard(members, indexed)
    return told, comp


def _links(pairs: DataFrame, sketches: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    with arrow_batches(pairs.sparkSession, 500):
        left = materialize(filtered(pairs, sketches, percent), "near-filtered")
        links = verified(left, texts, words, percent)
    discard(left)
    return links


def distinct_rows(docs: DataFrame) -> DataFrame:
    """``docs`` with ``_row``, a whole number that differs where id or text do: the id, unless texts share it or it is null."""
    text = F.coalesce(F.col("text"), F.lit(""))
    told = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.sha2(text, 256).alias("sha"))
    per_id = told.groupBy("doc_id").agg(F.min("sha").alias("low"), F.max("sha").alias("high"))
    shared = materialize(told.join(per_id.filter("doc_id is null or low <> high").select(F.col("doc_id").alias("_id")), F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi").distinct(), "near-shared-ids")
    if shared.isEmpty():
        return docs.withColumn("_row", F.col("doc_id").cast("bigint"))
    top = told.agg(F.max("doc_id")).head()[0] or 0
    numbers = global_index(shared, ["doc_id", "sha"], "n").select(F.col("doc_id").alias("_id"), F.col("sha").alias("_sha"), (F.col("n") + top + 1).alias("_number"))
    found = docs.join(numbers, F.col("doc_id").cast("bigint").eqNullSafe(F.col("_id")) & (F.sha2(text, 256) == F.col("_sha")), "left")
    return found.withColumn("_row", F.coalesce(F.col("_number"), F.col("doc_id").cast("bigint"))).drop("_id", "_sha", "_number")


def keep_one(docs: DataFrame, *, words: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs``, all columns, that are alone or come first in their component: the least id, ids that
    stand for several texts last."""
    held = distinct_rows(docs.select("doc_id", "text", F.struct(*docs.columns).alias("_all")))
    tables = _classes_and_components(held.select(F.col("_row").alias("doc_id"), "text"), words, percent, PART_BYTES, BUCKET_TOKENS)
    gone = materialize(_named(*tables).filter("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct(), "near-gone")
    discard(*tables)
    return held.join(gone, held["_row"] == gone["_gone"], "left_anti").select("_all.*")


def op5_near_dedup(spark, sf_dir):
    return components(load(spark, sf_dir, "documents", "doc_id", "text"))


SQL = r"""
with recursive w as materialized (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
sh as materialized (
  select distinct doc_id, case when len(w) >= 4 then array_to_string(list_slice(w, i, i + 3), ' ') else array_to_string(w, ' ') end as s
  from (select doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) as i from w where len(w) > 0)),
n as materialized (select doc_id, count(*) as n from sh group by doc_id),
met as materialized (select a.doc_id as x, b.doc_id as y, count(*) as k from sh a join sh b on a.s = b.s and a.doc_id < b.doc_id group by all),
link as materialized (select x, y from met join n p on p.doc_id = x join n q on q.doc_id = y where 100 * k >= 85 * (p.n + q.n - k)),
both_ways as materialized (select x as u, y as v from link union all select y, x from link),
comp(vid, c) using key (vid) as (
  select distinct doc_id, doc_id from documents
  union
  select l.v, min(comp.c) from comp join both_ways l on l.u = comp.vid join recurring.comp r on r.vid = l.v where comp.c < r.c group by l.v)
select d.doc_id, coalesce(n.n, 0) as n_shingles, comp.c as component_id from documents d left join n on n.doc_id = d.doc_id left join comp on comp.vid = d.doc_id
"""

QUERIES = {"op5_near_dedup": op5_near_dedup}
ORACLES = {"op5_near_dedup": SQL}
