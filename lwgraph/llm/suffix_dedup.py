"""Removal of repeated byte strings by common-prefix intervals of suffixes.

A byte goes when a ``length``-byte string that covers it also starts in a document with a
smaller id.  Three steps keep this exact without moving every suffix:

1. Every string of ``length`` bytes contains a minimizer: the least hash among its
   ``GRAM``-byte substrings.  Equal strings have equal minimizers, so only strings whose
   minimizer occurs in two documents can repeat.
2. Those strings meet others with the same minimizer, as short stretches of text, in one
   task; equal stretches count as one there.  Their suffixes of at least ``length`` bytes are
   brought into an order in which common prefixes stay together, the lengths of common prefixes
   of neighbours are taken, and a stack scan turns these into the tree of common-prefix
   intervals.  An interval whose occurrences differ in the byte to their left, or start
   where a stretch starts, cannot be extended: it is a repeat group, with all its occurrences.
   The smallest id of a group decides which of them go.  Any other interval is the tail of a
   group that starts further left, so that the groups alone account for every repeated string.
3. The marks return to their documents.

``remove_repeats`` applies the marks; ``repeat_groups`` returns the groups themselves.  Copies
of whole texts are settled by digest beforehand in the former.  Hashes only decide where strings
meet; equality is that of their bytes.

Defined results: a null text is empty; texts shorter than ``length`` keep all bytes; rows
with equal ids do not remove each other's bytes; a row with a null id neither removes nor
loses anything and is in no group; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, load, materialize, shuffle_width
from .packed import COUNT_SCHEMA, bucket_of, contains, count_rows, frequent_keys, merged_keys, mix64, pack48, unpack48
from .textbytes import byte_view, concat_column, release

LENGTH, GRAM = 50, 20
PART_BYTES = 12 << 20
SLICE = 1 << 20
_MASK48 = np.uint64((1 << 48) - 1)


def gram_hashes(data: np.ndarray, gram: int = GRAM) -> np.ndarray:
    """64-bit hash of the ``gram`` bytes that start at each position (16 to 24 bytes)."""
    n = len(data) - gram + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    data = np.ascontiguousarray(data)
    words = np.ndarray((len(data) - 7,), "<u8", data.data, strides=(1,))
    x = words[:n] * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x += words[8 : n + 8]
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    x += words[gram - 8 : n + gram - 8]
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(30)
    return x


def minimizer_runs(data: np.ndarray, offsets: np.ndarray, length: int, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(document, first start, last start, key) of maximal runs of ``length``-byte strings with one minimizer place."""
    h = gram_hashes(data, gram)
    span = length - gram + 1
    if len(h) < span:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),)
    low = (h & ~np.uint64(0xFFFFFFFF)) | np.arange(len(h), dtype=np.uint64)
    width = 1
    while width * 2 <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < span:
        low = np.minimum(low[: len(h) - span + 1], low[span - width : span - width + len(h) - span + 1])
    place = (low & np.uint64(0xFFFFFFFF)).astype(np.int64)
    sizes = np.diff(offsets)
    doc = np.repeat(np.arange(len(sizes)), sizes)[: len(place)]
    inside = np.arange(len(place)) + length <= offsets[doc + 1]
    step = np.flatnonzero(np.concatenate([[True], (place[1:] != place[:-1]) | (doc[1:] != doc[:-1]) | (inside[1:] != inside[:-1])]))
    last = np.append(step[1:], len(place)) - 1
    good = inside[step]
    first, last = step[good], last[good]
    return doc[first], first, last, mix64(h[place[first]]) & _MASK48


def _pieces(data: np.ndarray, offsets: np.ndarray):
    """Slices of whole documents of about SLICE bytes: (first document, bytes, offsets)."""
    i, rows = 0, len(offsets) - 1
    while i < rows:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + SLICE, "right")) - 1)
        yield i, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j


_KEEP = np.array([0, *((2**64 - 1) ^ (2 ** (64 - 8 * n) - 1) for n in range(1, 9))], np.uint64)  # the first n bytes of a word


def prefix_words(text: np.ndarray, start: np.ndarray, size: np.ndarray, first: int, stop: int) -> list[np.ndarray]:
    """Words first .. stop - 1 of the strings at ``start``, eight bytes each, in byte order; zero beyond their size.

    ``text`` goes on for 8 * stop bytes after the last start."""
    words = np.ndarray((len(text) - 7,), "<u8", np.ascontiguousarray(text).data, strides=(1,))
    return [words[np.minimum(start + 8 * w, len(words) - 1)].byteswap() & _KEEP[np.clip(size - 8 * w, 0, 8)] for w in range(first, stop)]


def common_prefixes(words: list[np.ndarray], size: np.ndarray, skipped: int) -> np.ndarray:
    """Bytes that each string shares with the one before it; all are known to share the first ``skipped`` words."""
    shared = np.full(len(size) - 1, 8 * skipped)
    going = np.ones(len(size) - 1, bool)
    for w in words:
        d = w[1:] ^ w[:-1]
        same = np.where(d == 0, 8, np.argmax(d.byteswap().view(np.uint8).reshape(-1, 8) != 0, axis=1))
        shared += np.where(going, same, 0)
        going &= d == 0
    return np.minimum(shared, np.minimum(size[1:], size[:-1]))


def interval_tree(lcp: list[int]) -> list[tuple[int, int, int]]:
    """(depth, first, last) of all intervals of a common-prefix array (lcp[0] belongs before the first suffix), inner ones first."""
    out, stack = [], [(0, 0)]  # depth, first
    for i in range(1, len(lcp) + 1):
        depth, begin = (lcp[i] if i < len(lcp) else 0), i - 1
        while stack[-1][0] > depth:
            d, begin = stack.pop()
            out.append((d, begin, i - 1))
        if stack[-1][0] < depth:
            stack.append((depth, begin))
    return out


def suffix_groups(text: np.ndarray, begin: np.ndarray, size: np.ndarray, keys: np.ndarray, length: int, windows: int = 300_000):
    """Repeat groups among distinct stretches, some at a time: (depth, number of members, stretch and place of every member).

    Suffixes that share ``length`` bytes come together by a hash of these bytes and are ordered by
    the bytes beyond; where a hash joins unequal strings, by all bytes."""
    counts, shared = size - length + 1, length // 8
    text = np.concatenate([text, np.zeros(2 * length + 8, np.uint8)])
    owner = np.repeat(np.arange(len(size)), counts)
    place = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    lead = mix64(keys)[owner]
    for a in range(0, len(owner), windows):
        o, p = owner[a : a + windows], place[a : a + windows]
        for w in prefix_words(text, begin[o] + p, np.full(len(o), length), 0, -(-length // 8)):
            lead[a : a + windows] = mix64(lead[a : a + windows]) + w
    order = np.argsort(lead, kind="stable")
    ranked = lead[order]
    edge = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1], [True]])[: len(ranked) + 1]) if len(ranked) else np.zeros(1, np.int64)
    several = np.diff(edge) > 1
    starts, stops = edge[:-1][several], edge[1:][several]
    done = np.cumsum(stops - starts)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(done, (done[i - 1] if i else 0) + windows, "right")))
        sizes = (stops - starts)[i:j]
        at = order[np.repeat(starts[i:j] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())]
        run, o, p = np.repeat(np.arange(j - i), sizes), owner[at], place[at]
        rest = size[o] - p
        head = prefix_words(text, begin[o] + p, np.full(len(o), length), 0, -(-length // 8))
        first = np.repeat(np.cumsum(sizes) - sizes, sizes)
        if any((h != h[first]).any() for h in head) or (keys[o] != keys[o][first]).any():
            run = np.unique(np.stack([run.astype(np.uint64), keys[o], *head], 1), axis=0, return_inverse=True)[1].reshape(-1)
        tail = prefix_words(text, begin[o] + p, rest, shared, -(-int(rest.max()) // 8))
        by = np.lexsort((rest, *reversed(tail), run))
        run, o, p, rest = run[by], o[by], p[by], rest[by]
        lcp = common_prefixes([t[by] for t in tail], rest, shared)
        lcp[run[1:] != run[:-1]] = 0
        left, clipped = text[np.maximum(begin[o] + p - 1, 0)], p == 0
        turns = np.concatenate([[0], np.cumsum((left[1:] != left[:-1]) | clipped[1:])])
        found = np.array(interval_tree([0, *lcp.tolist()]), np.int64).reshape(-1, 3)
        depth, f, z = found[:, 0], found[:, 1], found[:, 2]
        diverse = (turns[z] > turns[f]) | clipped[f]
        depth, f, n = depth[diverse], f[diverse], (z - f + 1)[diverse]
        members = np.repeat(f - (np.cumsum(n) - n), n) + np.arange(n.sum())
        if len(depth):
            yield depth, n, o[members], p[members]
        i = j


def part_runs(table: pa.Table, repeated: np.ndarray, length: int):
    """Runs of one part whose minimizer is repeated, and their distinct stretches.

    (ids, data, offsets, (row, first, last), stretch of each run, (key, least id, a run) of each stretch);
    stretches are numbered in the order of (key, content hash), which any recomputation repeats;
    equal ones are equal byte by byte."""
    ids = table.column("doc_id").to_numpy()
    data, offsets = byte_view(concat_column(table, "text"))
    got: list[tuple[np.ndarray, ...]] = [(np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2]
    for i, piece, off in _pieces(data, offsets):
        row, first, last, key = minimizer_runs(piece, off, length)
        hit = contains(repeated, key)
        if hit.any():
            row, first, last, key = row[hit], first[hit], last[hit], key[hit]
            h, stop = gram_hashes(piece), last + length - GRAM
            content = h[first]
            for k in range(1, -(-(2 * length - GRAM) // GRAM)):  # overlapping substrings that cover the stretch
                content = mix64(content) + h[np.minimum(first + k * GRAM, stop)]
            content = mix64(content + (last - first).astype(np.uint64))
            got.append((row + i, first + offsets[i], last + offsets[i], key, content))
    row, first, last, key, content = (np.concatenate(x) for x in zip(*got, strict=True))
    order = np.lexsort((content, key))
    k, c = key[order], content[order]
    differs = np.concatenate([[True], (k[1:] != k[:-1]) | (c[1:] != c[:-1])])[: len(k)]
    if len(k):
        parts = prefix_words(np.concatenate([data, np.zeros(2 * length, np.uint8)]), first[order], (last - first)[order] + length, 0, -(-2 * length // 8))
        unlike = np.concatenate([[False], (last - first)[order][1:] != (last - first)[order][:-1]])
        for w in parts:
            unlike[1:] |= w[1:] != w[:-1]
        if (unlike & ~differs).any():  # two strings under one hash: order by the bytes themselves
            order = np.lexsort((*(w[np.argsort(order)] for w in reversed(parts)), last - first, key))
            k = key[order]
            parts = prefix_words(np.concatenate([data, np.zeros(2 * length, np.uint8)]), first[order], (last - first)[order] + length, 0, -(-2 * length // 8))
            differs = np.concatenate([[True], (k[1:] != k[:-1]) | ((last - first)[order][1:] != (last - first)[order][:-1])])
            for w in parts:
                differs[1:] |= w[1:] != w[:-1]
    new = np.flatnonzero(differs)
    stretch = np.zeros(len(key), np.int64)
    stretch[order] = np.repeat(np.arange(len(new)), np.diff(np.append(new, len(k))))
    least = np.minimum.reduceat(ids[row[order]], new) if len(new) else np.zeros(0, np.int64)
    return ids, data, offsets, (row, first, last), stretch, (k[new], least, order[new])


def _bounds(keys: np.ndarray, buckets: int):
    edges = np.searchsorted(bucket_of(keys, buckets), np.arange(buckets + 1))
    return [(b, i, j) for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)) if j > i]


STRETCH_SCHEMA = "part int, bucket int, ids binary, sizes binary, keys binary, text binary"


def _stretches(part: int, table: pa.Table, repeated: np.ndarray, length: int, buckets: int) -> pa.Table:
    _, data, _, (_, first, last), _, (key, least, run) = part_runs(table, repeated, length)
    rows = []
    for b, i, j in _bounds(key, buckets):
        begin, size = first[run[i:j]], (last - first)[run[i:j]] + length
        at = np.repeat(begin - (np.cumsum(size) - size), size) + np.arange(size.sum())
        rows.append((part, b, least[i:j].astype("<i8").tobytes(), size.astype(np.uint8).tobytes(), pack48(key[i:j]), data[at].tobytes()))
    cols = list(zip(*rows, strict=True)) or [()] * 6
    return pa.table([pa.array(c, t) for c, t in zip(cols, [pa.int32()] * 2 + [pa.binary()] * 4, strict=True)], names=["part", "bucket", "ids", "sizes", "keys", "text"])


def _distinct(text: np.ndarray, begin: np.ndarray, sizes: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of the distinct stretch of each row, a row of each distinct stretch); stretches are equal by key and bytes."""
    padded = np.concatenate([text, np.zeros(int(sizes.max()) + 8, np.uint8)])
    words = prefix_words(padded, begin, sizes, 0, -(-int(sizes.max()) // 8))
    lead = mix64(keys) + sizes.astype(np.uint64)
    for w in words:
        lead = mix64(lead) + w
    order = np.argsort(lead, kind="stable")

    def steps(order: np.ndarray) -> np.ndarray:
        new = (keys[order][1:] != keys[order][:-1]) | (sizes[order][1:] != sizes[order][:-1])
        for w in words:
            new |= w[order][1:] != w[order][:-1]
        return new

    new = steps(order)
    if (new & (lead[order][1:] == lead[order][:-1])).any():
        order = np.lexsort((*reversed(words), sizes, keys))
        new = steps(order)
    number = np.zeros(len(order), np.int64)
    number[order] = np.concatenate([[0], np.cumsum(new)])
    return number, order[np.flatnonzero(np.concatenate([[True], new]))]


ANSWER_SCHEMA = "part int, bucket int, keys binary, masks binary, groups binary"


def _judge(table: pa.Table, length: int, with_groups: bool = False) -> pa.Table:
    """For each stretch a bit a string: set where a document below the stretch's own least id has that string.

    With ``with_groups`` also (stretch, place, depth, group) of every member of a repeat group; a stretch
    that several documents may share is a group too unless a longer row of members holds it."""
    cols = {k: table.column(k).to_pylist() for k in ("ids", "sizes", "keys", "text")}
    ids, keys = np.frombuffer(b"".join(cols["ids"]), "<i8"), np.concatenate([unpack48(x) for x in cols["keys"]])
    sizes, text = np.frombuffer(b"".join(cols["sizes"]), np.uint8).astype(np.int64), np.frombuffer(b"".join(cols["text"]), np.uint8)
    begin = np.cumsum(sizes) - sizes
    number, sample = _distinct(text, begin, sizes, keys)
    own = np.full(len(sample), np.iinfo(np.int64).max)
    np.minimum.at(own, number, ids)
    per_row = int(sizes.max()) - length + 1
    least = np.repeat(own[:, None], per_row, axis=1)  # the least id that has each string of a distinct stretch
    records, groups, whole = [], 0, np.zeros(len(sample), bool)
    for depth, n, stretch, place in suffix_groups(text, begin[sample], sizes[sample], keys[sample], length):
        first = np.cumsum(n) - n
        smallest = np.minimum.reduceat(own[stretch], first)
        spans = np.repeat(depth - length + 1, n)
        cell = np.repeat(stretch * per_row + place - (np.cumsum(spans) - spans), spans) + np.arange(spans.sum())
        np.minimum.at(least.reshape(-1), cell, np.repeat(np.repeat(smallest, n), spans))
        if with_groups:
            records.append(np.stack([stretch, place, np.repeat(depth, n), np.repeat(np.arange(groups, groups + len(n)), n)], 1))
            whole[stretch[(place == 0) & (np.repeat(depth, n) == sizes[sample][stretch])]] = True
            groups += len(n)
    masks = ((ids[:, None] > least[number]) @ (1 << np.arange(per_row, dtype=np.int64))).astype(np.uint32)
    edges = np.concatenate([[0], np.cumsum([len(x) // 8 for x in cols["ids"]])])
    blobs = pa.nulls(table.num_rows, pa.binary())
    if with_groups:
        alone = np.flatnonzero(~whole)
        records.append(np.stack([alone, np.zeros(len(alone), np.int64), sizes[sample][alone], np.arange(groups, groups + len(alone))], 1))
        told = np.concatenate(records)
        told = told[np.argsort(told[:, 0], kind="stable")]
        at = np.searchsorted(told[:, 0], np.arange(len(sample) + 1))
        out = []
        for a, b in zip(edges, edges[1:], strict=False):
            mine = [np.concatenate([np.full((at[g + 1] - at[g], 1), r), told[at[g] : at[g + 1], 1:]], 1) for r, g in enumerate(number[a:b])]
            out.append(np.concatenate(mine).astype("<i8").tobytes())
        blobs = pa.array(out, pa.binary())
    return pa.table({"part": table.column("part"), "bucket": table.column("bucket"), "keys": pa.nulls(table.num_rows, pa.binary()),
                     "masks": pa.array([masks[a:b].astype("<u4").tobytes() for a, b in zip(edges, edges[1:], strict=False)], pa.binary()), "groups": blobs})


def _cut(table: pa.Table, answers: pa.Table, length: int) -> pa.Table:
    told = answers.filter(pc.is_valid(answers.column("masks"))).sort_by("bucket")
    masks = np.frombuffer(b"".join(told.column("masks").to_pylist()), "<u4")
    ids, data, offsets, (row, first, last), stretch, (_, least, _) = part_runs(table, merged_keys(answers), length)
    counts = last - first + 1
    owner = np.repeat(np.arange(len(row)), counts)
    inner = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    gone = (ids[row] > least[stretch])[owner] | ((masks[stretch[owner]] >> inner.astype(np.uint32)) & 1).astype(bool)
    start = (first[owner] + inner)[gone]
    change = np.bincount(start, minlength=len(data) + 1)[: len(data) + 1] - np.bincount(start + length, minlength=len(data) + 1)[: len(data) + 1]
    covered = np.cumsum(change[:-1]) > 0
    removed, spans, digests = [], [], []
    for a, b in zip(offsets, offsets[1:], strict=False):
        g = covered[a:b]
        removed.append(int(g.sum()))
        spans.append(int((g[1:] & ~g[:-1]).sum() + (g[0] if len(g) else 0)))
        digests.append(hashlib.sha256(data[a:b][~g].tobytes()).hexdigest())
    return pa.table({"doc_id": pa.array(ids, pa.int64()), "n_bytes": pa.array(np.diff(offsets), pa.int64()), "n_removed": pa.array(removed, pa.int64()), "n_spans": pa.array(spans, pa.int64()), "kept_sha256": pa.array(digests, pa.string())})


def _occurrences(table: pa.Table, answers: pa.Table, length: int) -> pa.Table:
    """(bucket, number, depth, doc_id, start) of the members of repeat groups that lie in one part."""
    told = answers.filter(pc.is_valid(answers.column("groups"))).sort_by("bucket")
    ids, _, offsets, (row, first, _), stretch, _ = part_runs(table, merged_keys(answers), length)
    before, found = 0, [np.zeros((0, 5), np.int64)]
    for bucket, groups, masks in zip(told.column("bucket").to_pylist(), told.column("groups").to_pylist(), told.column("masks").to_pylist(), strict=True):
        r = np.frombuffer(groups, "<i8").reshape(-1, 4)
        found.append(np.concatenate([np.full((len(r), 1), bucket), r + [before, 0, 0, 0]], 1))
        before += len(masks) // 4
    bucket, which, place, depth, group = np.concatenate(found).T
    runs = np.argsort(stretch, kind="stable")
    at = np.searchsorted(stretch[runs], np.arange(before + 1))
    n = (at[1:] - at[:-1])[which] if before else np.zeros(0, np.int64)
    run = runs[np.repeat(at[which] - (np.cumsum(n) - n), n) + np.arange(n.sum())] if len(n) else np.zeros(0, np.int64)
    spread = lambda x: np.repeat(x, n)
    start = first[run] - offsets[row[run]] + spread(place)
    return pa.table({"bucket": pa.array(spread(bucket), pa.int32()), "number": pa.array(spread(group), pa.int64()), "depth": pa.array(spread(depth), pa.int32()), "doc_id": pa.array(ids[row[run]], pa.int64()), "start": pa.array(start, pa.int64())})


def _marked(moved: DataFrame, length: int, parts: int, with_groups: bool = False):
    """(texts by part, answers by part) for rows (part, doc_id, text).

    Keys and answers are written, so that the texts' exchange is gone before they are dealt once more."""
    grouped = moved.groupBy("part")

    def keys_of(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        data, offsets = byte_view(concat_column(table, "text"))
        found = []
        for _, piece, off in _pieces(data, offsets):
            doc, _, _, k = minimizer_runs(piece, off, length)
            found.append(np.unique((doc.astype(np.uint64) << np.uint64(48)) | k) & _MASK48)  # a slice has fewer than 2**16 texts this long
        release()
        return count_rows(key[0].as_py(), found, parts)

    repeated = materialize(frequent_keys(grouped.applyInArrow(keys_of, COUNT_SCHEMA), 2), "repeated-keys")

    def send(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        out = _stretches(key[0].as_py(), left, merged_keys(right), length, parts)
        release()
        return out

    def judge(table: pa.Table) -> pa.Table:
        out = _judge(table, length, with_groups)
        release()
        return out

    stretches = grouped.cogroup(repeated.groupBy("part")).applyInArrow(send, STRETCH_SCHEMA)
    judged = materialize(stretches.groupBy("bucket").applyInArrow(judge, ANSWER_SCHEMA), "judged")
    none = F.lit(None).cast("binary")
    answers = judged.unionByName(repeated.select("part", F.lit(0).alias("bucket"), "keys", none.alias("masks"), none.alias("groups")))
    return grouped, answers.groupBy("part")


def _dealt(rows: DataFrame, parts: int) -> DataFrame:
    return rows.select(F.pmod("doc_id", F.lit(parts)).cast("int").alias("part"), "doc_id", "text")


def _sized(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text"))


def repeat_groups(docs: DataFrame, *, length: int = LENGTH, part_bytes: int = PART_BYTES) -> DataFrame:
    """(group_id, depth, doc_id, start): every repeat group with all its occurrences, copies of whole texts among them.

    A group is a string of ``depth`` bytes, at least ``length``, that no byte to the left extends at all its
    occurrences within the stretches of one minimizer, at most 2 * length - GRAM bytes; a longer repeat
    is a row of groups that overlap in all but a few bytes, each with all occurrences."""
    rows = _sized(docs).filter(F.col("doc_id").isNotNull() & (F.octet_length("text") >= length))
    total = rows.agg(F.sum(F.octet_length("text").cast("bigint"))).head()[0] or 0
    parts = max(shuffle_width(docs.sparkSession), -(-total // part_bytes))

    def tell(left: pa.Table, right: pa.Table) -> pa.Table:
        out = _occurrences(left, right, length)
        release()
        return out

    grouped, answers = _marked(_dealt(rows, parts), length, parts, with_groups=True)
    found = materialize(grouped.cogroup(answers).applyInArrow(tell, "bucket int, number long, depth int, doc_id long, start long"), "repeat-groups")
    # a stretch that only one place has is no repeat
    real = found.groupBy("bucket", "number").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("bucket", "number")
    return found.join(real, ["bucket", "number"]).select(F.concat_ws("-", "bucket", "number").alias("group_id"), "depth", "doc_id", "start")


def remove_repeats(docs: DataFrame, *, length: int = LENGTH, part_bytes: int = PART_BYTES) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every row."""
    sized = _sized(docs)
    digests = materialize(sized.select("doc_id", F.octet_length("text").cast("bigint").alias("n_bytes"), F.sha2("text", 256).alias("sha")), "digests")
    firsts = digests.groupBy("sha").agg(F.min("doc_id").alias("first_id"), F.first("n_bytes").alias("n_bytes"))
    # two join keys: both sides are exchanged, so a hot group of copies can be split among tasks
    told = materialize(digests.join(firsts, ["sha", "n_bytes"]).select("doc_id", "n_bytes", "sha", "first_id"), "copies")
    discard(digests)
    copy = F.col("doc_id").isNotNull() & (F.col("doc_id") > F.col("first_id")) & (F.col("n_bytes") >= length)
    plain = F.col("doc_id").isNull() | (F.col("n_bytes") < length)
    settled = told.filter(copy | plain).select(
        "doc_id", "n_bytes", F.when(copy, F.col("n_bytes")).otherwise(0).alias("n_removed"), F.when(copy, 1).otherwise(0).cast("bigint").alias("n_spans"),
        F.when(copy, F.sha2(F.lit(""), 256)).otherwise(F.col("sha")).alias("kept_sha256"))
    total = told.agg(F.sum("n_bytes")).head()[0] or 0
    parts = max(shuffle_width(docs.sparkSession), -(-total // part_bytes))
    alone = told.filter(~(copy | plain)).select(F.col("doc_id").alias("keep"), F.col("sha").alias("keep_sha")).distinct()
    moved = sized.withColumn("sha", F.sha2("text", 256)).join(alone, (F.col("doc_id") == F.col("keep")) & (F.col("sha") == F.col("keep_sha")), "left_semi")

    def cut(left: pa.Table, right: pa.Table) -> pa.Table:
        out = _cut(left, right, length)
        release()
        return out

    grouped, answers = _marked(_dealt(moved, parts), length, parts)
    kept = grouped.cogroup(answers).applyInArrow(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    return kept.unionByName(settled)


def op8_suffix_dedup(spark, sf_dir):
    return remove_repeats(load(spark, sf_dir, "documents", "doc_id", "text"))


SQL = """
with b as materialized (select doc_id, encode(coalesce(text, '')) as t from documents),
k as materialized (select doc_id, i, array_slice(t, i + 1, i + 50) as s from (select doc_id, t, unnest(range(0, greatest(octet_length(t) - 49, 0))) as i from b)),
g as materialized (select k.doc_id, k.i from k join (select s, min(doc_id) as least from k group by s having min(doc_id) < max(doc_id)) f on f.s = k.s where f.least < k.doc_id),
runs as materialized (
  select doc_id, min(i) as a, max(i) + 50 as z
  from (select doc_id, i, sum(fresh) over (partition by doc_id order by i rows unbounded preceding) as run
        from (select doc_id, i, case when i <= lag(i) over (partition by doc_id order by i) + 50 then 0 else 1 end as fresh from g))
  group by doc_id, run),
kept as materialized (
  select doc_id, coalesce(lag(z) over (partition by doc_id order by a), 0) as a, a as z from runs
  union all
  select b.doc_id, coalesce(r.z, 0), octet_length(b.t) from b left join (select doc_id, max(z) as z from runs group by doc_id) r on r.doc_id = b.doc_id),
texts as (select b.doc_id, string_agg(hex(array_slice(b.t, k.a + 1, k.z)), '' order by k.a) as h from b join kept k on k.doc_id = b.doc_id where k.z > k.a group by b.doc_id)
select b.doc_id, octet_length(b.t) as n_bytes, cast(coalesce(r.n, 0) as bigint) as n_removed, coalesce(r.spans, 0) as n_spans, sha256(unhex(coalesce(x.h, ''))) as kept_sha256
from b left join (select doc_id, sum(z - a) as n, count(*) as spans from runs group by doc_id) r on r.doc_id = b.doc_id left join texts x on x.doc_id = b.doc_id
"""

QUERIES = {"op8_suffix_dedup": op8_suffix_dedup}
ORACLES = {"op8_suffix_dedup": SQL}
