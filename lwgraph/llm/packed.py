"""Counting many small keys by packed rows.

Each group of documents ("part") sends its distinct keys, cut into ranges ("buckets"),
as one binary row a bucket, six bytes a key and one for the number of its documents.
A bucket adds the numbers up and answers every part with those of its keys that reach a
limit.  The answer is a property of the key alone, whatever part asks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

KEY_BITS = 48
COUNT_SCHEMA = "part int, bucket int, keys binary, counts binary"


def mix64(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def pack48(keys: np.ndarray) -> bytes:
    return np.ascontiguousarray(keys.astype("<u8").view("<u2").reshape(-1, 4)[:, :3]).tobytes()


def unpack48(data: bytes) -> np.ndarray:
    small = np.frombuffer(data, "<u2").reshape(-1, 3)
    wide = np.zeros((len(small), 4), "<u2")
    wide[:, :3] = small
    return wide.reshape(-1).view("<u8")


def bucket_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    return ((keys >> np.uint64(16)) * np.uint64(buckets) >> np.uint64(KEY_BITS - 16)).astype(np.int64)


def count_rows(part: int, per_document: list[np.ndarray], buckets: int) -> pa.Table:
    """Rows for one part from the distinct 48-bit keys of each of its documents."""
    flat = np.concatenate([np.zeros(0, np.uint64), *per_document])
    keys, counts = np.unique(flat, return_counts=True)
    edges = np.searchsorted(bucket_of(keys, buckets), np.arange(buckets + 1))
    rows = [(b, pack48(keys[i:j]), np.minimum(counts[i:j], 255).astype(np.uint8).tobytes()) for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)) if j > i]
    return pa.table({"part": pa.array([part] * len(rows), pa.int32()), "bucket": pa.array([r[0] for r in rows], pa.int32()), "keys": pa.array([r[1] for r in rows], pa.binary()), "counts": pa.array([r[2] for r in rows], pa.binary())})


def frequent_keys(sent: DataFrame, least: int) -> DataFrame:
    """(part, keys): the keys of each part that at least ``least`` documents hold."""

    def answer(table: pa.Table) -> pa.Table:
        blobs = table.column("keys").to_pylist()
        keys = np.concatenate([unpack48(b) for b in blobs])
        counts = np.concatenate([np.frombuffer(c, np.uint8) for c in table.column("counts").to_pylist()]).astype(np.int64)
        row = np.repeat(np.arange(len(blobs)), [len(b) // 6 for b in blobs])
        order = np.argsort(keys, kind="stable")
        s = keys[order]
        first = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
        total = np.add.reduceat(counts[order], first)
        often = np.zeros(len(keys), bool)
        often[order] = np.repeat(total >= least, np.diff(np.append(first, len(s))))
        parts = table.column("part").to_pylist()
        edges = np.searchsorted(row, np.arange(len(blobs) + 1))
        out = [(p, pack48(keys[i:j][often[i:j]])) for p, i, j in zip(parts, edges, edges[1:], strict=False) if often[i:j].any()]
        return pa.table({"part": pa.array([o[0] for o in out], pa.int32()), "keys": pa.array([o[1] for o in out], pa.binary())})

    return sent.groupBy("bucket").applyInArrow(answer, "part int, keys binary")


def merged_keys(table: pa.Table, column: str = "keys") -> np.ndarray:
    """All keys of an answer, sorted."""
    return np.sort(np.concatenate([np.zeros(0, np.uint64), *(unpack48(b) for b in table.column(column).to_pylist() if b)]))


def contains(sorted_keys: np.ndarray, keys: np.ndarray) -> np.ndarray:
    if not len(sorted_keys):
        return np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(sorted_keys, keys), len(sorted_keys) - 1)
    return sorted_keys[at] == keys
