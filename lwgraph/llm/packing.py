"""Packing along a space-filling curve.

Every document becomes token ids and a hashed vector of them, projected to a few
dimensions; the Hilbert index of the projected point is its place on the curve.
Documents are sorted by that index and laid end to end; cutting the line every
``length`` ids gives the sequences.  Only the last sequence of the whole corpus can be
short; it is cut into powers of two, so nothing is padded.

With a ``stretch`` column the corpus has an order of its own: stretches follow each other by
its number, and the curve orders the documents inside each stretch only.

Order and offsets use narrow rows only: a range sort by (stretch, curve key, id), sums per sorted
partition, offsets of partitions.  The ids cross the network once, as 16-bit words, to meet their
offsets.

Tokens come from a word cache: the tokenizer's normaliser and splitter are applied to
the text, and each distinct word goes through the tokenizer once per worker.  Texts that hold
the special tokens' strings go through the tokenizer whole.

Defined results: a null text is an empty document of one end token; repeated ids are
packed as separate rows; other columns are ignored; an empty table gives no pieces.
"""

from __future__ import annotations

import functools
import os
import re
import sys
import unicodedata
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_batches, load, materialize, shuffle_width
from .textbytes import releasing, slices

LENGTH, END_ID = 2048, 1
HASHED, PROJECTED, BITS = 64, 3, 16
CACHE_WORDS = 400_000

# The word pattern of the vocabulary file.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
SPECIAL = ("<|startoftext|>", "<|endoftext|>")


# The same pattern for the standard library's engine: LATIN_WORDS where all characters are below U+0100, PLAIN_WORDS
# below U+0250, both only where every numeric character is a decimal digit.
LATIN_WORDS = re.compile(r"[a-z\xaa\xb5\xba\xdf-\xf6\xf8-\xff]+|'(?:s|t|re|ve|m|ll|d)|[0-9]|(?:[^\s\w]|_)+")
PLAIN_WORDS = re.compile(r"'(?:s|t|re|ve|m|ll|d)|[^\W\d_]+|\d|(?:[^\s\w]|_)+")
_BEYOND_LATIN = re.compile("[\x1c-\x1f\u00b2\u00b3\u00b9\u00bc-\u00be\u0100-\U0010ffff]")
_BEYOND_PLAIN = re.compile("[\x1c-\x1f\u00b2\u00b3\u00b9\u00bc-\u00be\u0250-\U0010ffff]")


@functools.cache
def _unsettled() -> re.Pattern:
    """Code points without a category here: a newer Unicode of the tokenizer may class them otherwise; and the separators U+001C to U+001F."""
    none = [c for c in range(sys.maxunicode + 1) if unicodedata.category(chr(c)) == "Cn"]
    starts = [c for c, before in zip(none, [-2, *none], strict=False) if c != before + 1]
    ends = [c for c, after in zip(none, [*none[1:], -2], strict=True) if c != after - 1]
    return re.compile("[\\x1c-\\x1f" + "".join(f"\\U{a:08x}-\\U{z:08x}" for a, z in zip(starts, ends, strict=True)) + "]")


class WordCache:
    """Ids of whole texts, through a bounded cache of the ids of words."""

    def __init__(self, path: str, limit: int = CACHE_WORDS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks share the cores already
        import regex
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel, Sequence, WhitespaceSplit

        self.tokenizer = Tokenizer.from_file(path)
        self.of_words = Tokenizer.from_file(path)  # for words that are normalised and split already
        self.of_words.normalizer = None
        self.of_words.pre_tokenizer = Sequence([WhitespaceSplit(), ByteLevel(add_prefix_space=False, use_regex=False)])
        self.limit, self.known, self.find = limit, {}, regex.compile(WORDS).findall
        self.ends = np.zeros(self.tokenizer.get_vocab_size(), bool)  # ids that end a word
        self.ends[[i for t, i in self.tokenizer.get_vocab().items() if t.endswith("</w>")]] = True

    def words(self, text: str) -> list[str] | None:
        """The normalised words, or None where only the tokenizer itself can tell."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
        text = text.lower() if "Σ" not in text else "".join(c.lower() for c in text)
        if not _BEYOND_LATIN.search(text):
            return LATIN_WORDS.findall(text)
        if not _BEYOND_PLAIN.search(text):
            return PLAIN_WORDS.findall(text)
        return None if _unsettled().search(text) else self.find(text)

    def learn(self, fresh: list[str]) -> None:
        """Tokenize new words, some hundred to a text; every word ends in an id that marks a word's end."""
        for k in range(0, len(fresh), 1 << 14):
            part = fresh[k : k + (1 << 14)]
            made = self.of_words.encode_batch_fast([" ".join(part[i : i + 256]) for i in range(0, len(part), 256)], add_special_tokens=False)
            flat = np.concatenate([np.array(e.ids, "<u2") for e in made])
            stops = np.flatnonzero(self.ends[flat]) + 1
            if len(stops) == len(part) and (not len(stops) or stops[-1] == len(flat)):
                data, at = flat.tobytes(), (2 * stops).tolist()
                self.known.update(zip(part, (data[i:j] for i, j in zip([0, *at], at, strict=False)), strict=True))
            else:
                for w in part:
                    self.known[w] = np.array(self.tokenizer.encode(w, add_special_tokens=False).ids, "<u2").tobytes()

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.known) > self.limit:
            self.known.clear()
        get, out, waiting, fresh = self.known.get, [], [], set()
        for t in texts:
            w = None if "<|" in t and any(s in t.lower() for s in SPECIAL) else self.words(t)
            if w is None:
                out.append(np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, "<u2").tobytes())
                continue
            parts = list(map(get, w))
            try:
                out.append(b"".join(parts))
            except TypeError:  # a word that is not known yet
                gaps = [k for k, p in enumerate(parts) if p is None]
                fresh.update([w[k] for k in gaps])
                waiting.append((len(out), parts, gaps, [w[k] for k in gaps]))
                out.append(b"")
        self.learn(list(fresh))
        for at, parts, gaps, missed in waiting:
            for k, word in zip(gaps, missed, strict=True):
                parts[k] = get(word)
            out[at] = b"".join(parts)
        return [np.frombuffer(p, "<u2") for p in out]


_CACHES: dict[str, WordCache] = {}


def worker_cache(path: str) -> WordCache:
    """One bounded cache a worker process: words met by earlier tasks are known already."""
    if path not in _CACHES:
        _CACHES[path] = WordCache(path)
    return _CACHES[path]


def hilbert_index(points: np.ndarray, bits: int) -> np.ndarray:
    """Place on the Hilbert curve of points (rows x dims of whole numbers below 2**bits); Skilling's transform on columns."""
    x = points.astype(np.uint64).T.copy()
    dims = len(x)
    one = np.uint64(1)
    q = one << np.uint64(bits - 1)
    while q > one:
        p = q - one
        for i in range(dims):
            high = (x[i] & q) != 0
            swap = np.where(high, np.uint64(0), (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ swap)
            x[i] ^= swap
        q >>= one
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    carry, q = np.zeros_like(x[0]), one << np.uint64(bits - 1)
    while q > one:
        carry = np.where((x[dims - 1] & q) != 0, carry ^ (q - one), carry)
        q >>= one
    x ^= carry
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            out = (out << one) | ((x[i] >> np.uint64(b)) & one)
    return out


def curve_keys(ids: list[np.ndarray], seed: int = 11) -> np.ndarray:
    """Hilbert keys of documents from hashed, signed counts of their ids."""
    n = len(ids)
    if not n:
        return np.zeros(0, np.int64)
    flat = np.concatenate(ids)
    every = np.arange(1 << 16, dtype=np.uint32)
    mixed = (every * np.uint32(0x9E3779B1)) ^ (every * np.uint32(0x85EBCA6B) >> np.uint32(13))
    cell = ((mixed >> np.uint32(8)) % np.uint32(HASHED)).astype(np.int32)
    sign = 1.0 - 2.0 * ((mixed >> np.uint32(3)) & np.uint32(1))
    row = np.repeat(np.arange(n, dtype=np.int32) * HASHED, [len(i) for i in ids])
    vectors = np.bincount(row + cell[flat], sign[flat], n * HASHED).reshape(n, HASHED)
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
    points = vectors @ np.random.default_rng(seed).standard_normal((HASHED, PROJECTED)) / 2
    whole = np.clip((np.tanh(points) + 1) / 2 * (1 << BITS), 0, (1 << BITS) - 1).astype(np.uint64)
    return hilbert_index(whole, BITS).astype(np.int64)


def tokenised(docs: DataFrame, path: str, stretch: str | None = None) -> DataFrame:
    """(row_key, doc_id, curve_key, n, ids and the stretch column) with 16-bit little-endian ids that end with the end token."""
    more = [stretch] if stretch else []

    def run(batches):
        cache, key = worker_cache(path), TaskContext.get().partitionId() << 33
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                ids = [np.append(i, np.uint16(END_ID)) for i in cache.encode([t or "" for t in part.column("text").to_pylist()])]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(range(key, key + len(ids)), pa.int64()), part.column("doc_id"), pa.array(curve_keys(ids)), pa.array([len(i) for i in ids], pa.int64()), pa.array([i.astype("<u2").tobytes() for i in ids], pa.binary()), *(part.column(c) for c in more)],
                    names=["row_key", "doc_id", "curve_key", "n", "ids", *more])
                key += len(ids)

    kind = dict(docs.dtypes)["doc_id"]
    held = docs.select("doc_id", "text", *(F.col(c).cast("long").alias(c) for c in more))
    return held.mapInArrow(releasing(run), f"row_key long, doc_id {kind}, curve_key long, n long, ids binary" + "".join(f", `{c}` long" for c in more))


def line_starts(tokens: DataFrame, stretch: str | None = None) -> tuple[DataFrame, int]:
    """((row_key, start) along the curve, stretch after stretch, total ids)."""
    line = [*([stretch] if stretch else []), "curve_key", "doc_id", "row_key"]
    width = shuffle_width(tokens.sparkSession)

    def running(batches):
        total = 0
        for b in batches:
            ends = np.cumsum(b.column("n").to_numpy()) + total
            total = int(ends[-1]) if len(ends) else total
            yield pa.RecordBatch.from_arrays([b.column("part"), b.column("row_key"), b.column("n"), pa.array(ends, pa.int64())], names=["part", "row_key", "n", "ends"])

    ordered = (tokens.select("n", *line).repartitionByRange(width, *line)
               .sortWithinPartitions(*line).select(F.spark_partition_id().alias("part"), "row_key", "n")
               .mapInArrow(running, "part int, row_key long, n long, ends long"))
    local = materialize(ordered, "pack-order")
    # one row a partition: the driver adds them up
    sums = sorted((r["part"], r["total"]) for r in local.groupBy("part").agg(F.max("ends").alias("total")).collect())
    before, rows = 0, []
    for part, total in sums:
        rows.append((part, before))
        before += total
    offsets = tokens.sparkSession.createDataFrame(rows, "part int, before long")
    return local.join(F.broadcast(offsets), "part").select("row_key", (F.col("before") + F.col("ends") - F.col("n")).alias("line_start")), before


def cut_points(start: int, stop: int, total: int, length: int) -> list[int]:
    """Starts of the sequences that the span [start, stop) meets, then the end; the tail is cut into powers of two."""
    tail = total // length * length
    cuts, at = [], start // length * length if start < tail else None
    if at is None:
        at, rest = tail, total - tail
        while at + (1 << (rest.bit_length() - 1)) <= start:
            step = 1 << (rest.bit_length() - 1)
            at, rest = at + step, rest - step
    while at < stop:
        cuts.append(at)
        if at < tail:
            at += length
        else:
            rest = total - at
            at += 1 << (rest.bit_length() - 1)
    return [*cuts, at]


def pack(docs: DataFrame, path: str, *, length: int = LENGTH, with_ids: bool = False, stretch: str | None = None) -> DataFrame:
    """Pieces of documents: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, curve_key (and the ids on request).

    ``stretch`` names a column of whole numbers that the sequences follow before the curve."""
    with arrow_batches(docs.sparkSession, 2000):
        tokens = materialize(tokenised(docs, path, stretch), "pack-tokens")
    starts, total = line_starts(tokens, stretch)
    joined = tokens.join(starts, "row_key").select("doc_id", "curve_key", "ids", "line_start")
    full = total // length

    def cut(batches):
        for b in batches:
            cols = {k: [] for k in ("row", "start", "length", "crc", "doc_tokens", "sequence_id", "offset", "ids")}
            for row, (ids, first) in enumerate(zip(b.column("ids"), b.column("line_start").to_numpy(), strict=True)):
                words = np.frombuffer(ids.as_buffer(), "<u2")
                n, first = len(words), int(first)
                points = cut_points(first, first + n, total, length)
                for a, z in zip(points, points[1:], strict=False):
                    lo, hi = max(a, first), min(z, first + n)
                    piece = words[lo - first : hi - first].astype("<u4").tobytes()
                    cols["row"].append(row)
                    cols["start"].append(lo - first)
                    cols["length"].append(hi - lo)
                    cols["crc"].append(zlib.crc32(piece))
                    cols["doc_tokens"].append(n)
                    cols["sequence_id"].append(a // length if a < full * length else full + bin((total - full * length) >> (z - a).bit_length()).count("1"))
                    cols["offset"].append(lo - a)
                    if with_ids:
                        cols["ids"].append(piece)
            rows = pa.array(cols["row"], pa.int64())
            arrays = [b.column("doc_id").take(rows), *(pa.array(cols[k], pa.int64()) for k in ("start", "length", "crc", "doc_tokens", "sequence_id", "offset")), b.column("curve_key").take(rows)]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "curve_key"]
            if with_ids:
                arrays, names = [*arrays, pa.array(cols["ids"], pa.binary())], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    kind = dict(docs.dtypes)["doc_id"]
    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, curve_key long" + ", ids binary" * with_ids
    return joined.mapInArrow(releasing(cut), schema)


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op2_packing(spark, sf_dir):
    return pack(load(spark, sf_dir, "documents", "doc_id", "text"), vocabulary())


QUERIES = {"op2_packing": op2_packing}
ORACLES: dict[str, str] = {}
