"""Language identification by string kernels.

A text is the set of its byte n-grams (lengths 1 to 3, hashed): the blended-spectrum
presence kernel of two texts is the number of shared n-grams over the geometric mean
of their numbers.  A stratified set of landmarks gives the Nyström map, a ridge
regression of each language against the rest is solved in it, and since the kernel is
linear in the presence vectors the whole model folds into one matrix, applied to
batches of presence vectors.

Learning uses at most ``per_language`` rows of each of the ``max_languages`` most frequent
languages, taken by hash of the id among texts of 1 to ``max_text_bytes`` bytes.

Defined results: ``und`` with score 0 for null texts and texts without a letter, and for
every text when there is nothing to learn from; a null doc_id is not held out and not
learned from; of texts that share an id and a language the one that sorts first is learned
from; other input columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .textbytes import byte_view, releasing, slices

DIMENSIONS = 1 << 13
LENGTHS = (1, 2, 3)
PER_LANGUAGE = 300
LANDMARKS_PER_LANGUAGE = 40
MAX_LANGUAGES, MAX_TEXT_BYTES, CELLS = 100, 32 << 10, 8
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_FOLD[[9, 10, 11, 12, 13]] = 32


def presence(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Presence vectors (rows x DIMENSIONS, float32) of the n-grams of each text."""
    rows = len(offsets) - 1
    out = np.zeros(rows * DIMENSIONS, np.float32)
    if not len(data):
        return out.reshape(rows, DIMENSIONS)
    folded = _FOLD[data].astype(np.uint32)
    base = np.repeat(np.arange(rows, dtype=np.int64) * DIMENSIONS, np.diff(offsets))
    code = np.zeros(len(folded), np.uint32)
    for n in range(1, max(LENGTHS) + 1):
        code = folded if n == 1 else (code[:-1] << np.uint32(8)) | folded[n - 1 :]
        if n in LENGTHS:
            cell = ((code + np.uint32(n * 0x3D4D51CB & 0xFFFFFFFF)) * np.uint32(0x9E3779B1)) >> np.uint32(32 - (DIMENSIONS.bit_length() - 1))
            first = base[: len(code)]
            at = first + cell
            inside = first == base[n - 1 :]
            out[at if inside.all() else at[inside]] = 1
    return out.reshape(rows, DIMENSIONS)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.sqrt(x.sum(1, keepdims=True)), 1)


@dataclass
class KernelModel:
    languages: list[str]
    matrix: np.ndarray  # DIMENSIONS x languages
    offset: np.ndarray

    def outputs(self, x: np.ndarray) -> np.ndarray:
        return unit(x) @ self.matrix + self.offset


def fit(texts: list[bytes], langs: list[str], *, landmarks_per_language: int = LANDMARKS_PER_LANGUAGE, ridge: float = 1e-3) -> KernelModel | None:
    names = sorted(set(langs))
    if not names:
        return None
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
    data = np.frombuffer(b"".join(texts), np.uint8)

    def dense(rows: np.ndarray) -> np.ndarray:
        return unit(np.concatenate([presence(data[offsets[i] : offsets[i + 1]], offsets[i : i + 2] - offsets[i]) for i in rows]))

    which = np.array([names.index(v) for v in langs])
    marks = np.concatenate([np.flatnonzero(which == k)[:landmarks_per_language] for k in range(len(names))])
    lm = dense(marks)
    values, vectors = np.linalg.eigh((lm @ lm.T).astype(np.float64))
    good = values > max(values.max(), 1e-12) * 1e-7
    root = vectors[:, good] / np.sqrt(values[good])  # kernel to landmarks -> Nyström features
    every = np.arange(len(texts))
    z = np.concatenate([(dense(every[i : i + 256]) @ lm.T) @ root for i in range(0, len(texts), 256)])  # only landmarks stay as dense vectors
    mean = z.mean(0)
    targets = np.eye(len(names))[which]
    solved = np.linalg.solve((z - mean).T @ (z - mean) + ridge * len(z) * np.eye(z.shape[1]), (z - mean).T @ (targets - targets.mean(0)))
    matrix = lm.T @ (root @ solved)
    return KernelModel(names, matrix.astype(np.float32), (targets.mean(0) - mean @ solved).astype(np.float32))


def held_out(doc_id="doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def train(docs: DataFrame, *, per_language: int = PER_LANGUAGE, max_languages: int = MAX_LANGUAGES, max_text_bytes: int = MAX_TEXT_BYTES) -> KernelModel | None:
    size = F.octet_length("text")
    usable = docs.select(F.col("doc_id").alias("_id"), F.col("lang").alias("_lang"), "text").filter("_id is not null and _lang is not null").filter(~held_out("_id")).filter((size > 0) & (size <= max_text_bytes))
    common = usable.groupBy("_lang").agg(F.count(F.lit(1)).alias("_rows")).orderBy(F.desc("_rows"), "_lang").limit(max_languages).select("_lang")
    known = usable.select("_id", "_lang").join(F.broadcast(common), "_lang").distinct()
    # the first by hash in each of some cells of a language, then the first of these: no task sees a language whole
    first = lambda *parts: F.row_number().over(Window.partitionBy(*parts).orderBy(F.xxhash64("_id"), "_id"))
    few = known.withColumn("_cell", F.pmod(F.xxhash64("_id", F.lit(1)), F.lit(CELLS))).withColumn("_n", first("_lang", "_cell")).filter(F.col("_n") <= per_language)
    chosen = few.drop("_cell", "_n").withColumn("_n", first("_lang")).filter(F.col("_n") <= per_language)
    rows = usable.join(F.broadcast(chosen), ["_id", "_lang"]).groupBy("_id", "_lang", "_n").agg(F.min(F.col("text")).cast("binary").alias("text")).toArrow().sort_by([("_lang", "ascending"), ("_n", "ascending")])
    return fit(rows.column("text").to_pylist(), rows.column("_lang").to_pylist())


def _has_letter(text: str | None) -> bool:
    return bool(text) and any(c.isalpha() for c in text)


def predict(docs: DataFrame, model: KernelModel | None) -> DataFrame:
    """doc_id, lang_pred, score of every row."""

    def run(batches):
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                for k in range(0, part.num_rows, 256):
                    piece = part.slice(k, 256)
                    known = np.array([_has_letter(t) for t in piece.column("text").to_pylist()], bool)
                    names, scores = np.full(piece.num_rows, "und", object), np.zeros(piece.num_rows)
                    if model is not None:
                        out = model.outputs(presence(*byte_view(piece.column("text"))))
                        best = out.argmax(1)
                        names[known] = np.array(model.languages, object)[best[known]]
                        scores[known] = np.clip(out[np.arange(len(best)), best], 0, 1)[known]
                    yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "lang_pred", "score"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(releasing(run), f"doc_id {kind}, lang_pred string, score double")


def op9_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return predict(docs, train(docs)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


QUERIES = {"op9_language_id": op9_language_id}
ORACLES: dict[str, str] = {}
