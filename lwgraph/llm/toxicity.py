"""Toxicity from a weighted lexicon, matched by an Aho-Corasick automaton.

Texts are folded first: compatibility forms, case, marks above and below letters, look-alike
letters of other scripts, digits and signs that stand for letters, invisible characters; what
is not a letter then separates words.  The lexicon holds whole words and word beginnings with
log-odds weights; a hit inside an exception phrase does not count.  The weighted sum
and the same sum per length feed a two-feature logistic curve.

Learning uses at most ``max_rows`` labelled rows (a bounded sample by hash of the id) of at most
``max_text_bytes`` bytes each and never sees held-out rows.  Scoring reads every whole text.

Defined results: null and empty texts score like a text without hits; rows with null
labels are not learned from; repeated labels of a document count once, and of texts that share
an id the one that sorts first is learned from; without any toxic label the lexicon is empty and
every score is 0; other input columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textbytes import releasing, slices

THRESHOLD = 0.3
MAX_ROWS, MAX_TEXT_BYTES = 8000, 32 << 10

# Letters of other scripts that look like Latin ones, and signs used for letters.
LOOKALIKES = {
    "а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "і": "i", "ј": "j", "ѕ": "s", "к": "k", "м": "m", "т": "t", "в": "b", "н": "h",
    "ԁ": "d", "һ": "h", "ԛ": "q", "ԝ": "w", "ѵ": "v", "ь": "b", "г": "r", "п": "n", "ӏ": "l", "ԍ": "g", "є": "e", "ү": "y",
    "α": "a", "β": "b", "γ": "y", "ε": "e", "η": "n", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "ν": "v", "ι": "i", "κ": "k", "χ": "x", "ω": "w", "σ": "o",
    "օ": "o", "ս": "u", "ո": "n", "հ": "h", "ց": "g", "զ": "q", "յ": "j", "ք": "p",
    "ı": "i", "ɡ": "g", "ɑ": "a", "ʏ": "y", "ɪ": "i", "ʟ": "l", "ɴ": "n", "ʀ": "r", "ʙ": "b", "ɢ": "g", "ʜ": "h", "ø": "o", "đ": "d", "ħ": "h", "ł": "l", "ŧ": "t",
    "ᴀ": "a", "ᴄ": "c", "ᴅ": "d", "ᴇ": "e", "ᴊ": "j", "ᴋ": "k", "ᴍ": "m", "ᴏ": "o", "ᴘ": "p", "ᴛ": "t", "ᴜ": "u", "ᴠ": "v", "ᴡ": "w", "ᴢ": "z",
    "0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i", "|": "l",
}
INVISIBLE = "​‌‍⁠﻿­"
_TABLE = str.maketrans({**LOOKALIKES, **dict.fromkeys(INVISIBLE)})
_MARKS = re.compile("[\u0300-\u036f\u0483-\u0489\u1ab0-\u1aff\u1dc0-\u1dff\u20d0-\u20ff\ufe00-\ufe0f\ufe20-\ufe2f]+")
_SIGN_IN_WORD = re.compile(r"(?<=[^\W\d_])[!|](?=[^\W\d_])")
_NOT_LETTER = re.compile(r"[\W\d_]+")
_SIGNS_ALONE = str.maketrans({"!": " ", "|": " "})


def fold(text: str | None) -> str:
    """Words of letters only, separated and surrounded by single spaces."""
    if not text:
        return " "
    if text.isascii():
        text = text.lower()
    else:  # compatibility forms hide capitals, and small letters can decompose again
        text = _MARKS.sub("", unicodedata.normalize("NFKD", unicodedata.normalize("NFKD", text).lower()))
    if "!" in text or "|" in text:
        text = _SIGN_IN_WORD.sub(lambda m: "i" if m[0] == "!" else "l", text).translate(_SIGNS_ALONE)
    return f" {_NOT_LETTER.sub(' ', text.translate(_TABLE)).strip()} "


@dataclass
class ToxicLexicon:
    """Patterns start with a space (word start); whole words end with one too."""

    weights: dict[str, float] = field(default_factory=dict)
    exceptions: tuple[str, ...] = ()
    curve: tuple[float, float, float] = (-20.0, 0.0, 0.0)

    def automaton(self):
        import ahocorasick

        made = ahocorasick.Automaton()
        for p, w in self.weights.items():
            made.add_word(p, (len(p), w))
        for p in self.exceptions:
            made.add_word(f" {p} ", (len(p) + 2, None))  # a phrase that is a pattern too is spared
        made.make_automaton()
        return made

    def hits(self, folded: str, automaton) -> float:
        if not len(automaton):
            return 0.0
        found, spared = [], []
        for end, (size, weight) in automaton.iter(folded):
            (spared if weight is None else found).append((end - size + 1, end, weight))
        if spared:
            found = [x for x in found if not any(a <= x[0] and x[1] <= b for a, b, _ in spared)]
        return sum(w for _, _, w in found)

    def score(self, total: float, n_words: int) -> float:
        a, b, c = self.curve
        z = a + b * math.log1p(total) + c * math.log1p(100 * total / max(1, n_words))
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def _parts(folded: str) -> set[str]:
    out = set()
    for w in set(folded.split()):
        out.add(f" {w} ")
        out.update(f" {w[:k]}" for k in range(4, min(len(w), 8) + 1))
    return out


def learn(texts: list[str], marks: list[int], *, least_docs: int = 3, least_odds: float = 3.0, least_exception: int = 3) -> ToxicLexicon:
    n1 = sum(marks)
    n0 = len(marks) - n1
    if not n1 or not n0:
        return ToxicLexicon()
    folded = [fold(t) for t in texts]
    bad, good = Counter(), Counter()
    for t, y in zip(folded, marks, strict=True):
        if y:
            bad.update(_parts(t))
    wanted = {p for p, n in bad.items() if n >= least_docs}
    for t, y in zip(folded, marks, strict=True):
        if not y:
            good.update(wanted.intersection(_parts(t)))
    odds = {p: math.log((bad[p] + 0.5) / (n1 + 1)) - math.log((good[p] + 0.5) / (n0 + 1)) for p in wanted}
    kept: dict[str, float] = {}
    for p in sorted((p for p in odds if odds[p] >= least_odds), key=lambda p: (len(p.strip()), p)):
        stem = p.strip()
        # a beginning that is as telling already stands for its longer forms
        if not any(f" {stem[:k]}" in kept for k in range(4, len(stem) + 1)):
            kept[p] = odds[p]
    model = ToxicLexicon(kept)
    around_good, around_bad = Counter(), Counter()
    starts = tuple(kept)
    for t, y in zip(folded, marks, strict=True):
        if not any(p in t for p in starts):
            continue
        words = t.split()
        pairs = set()
        for i, w in enumerate(words):
            if f" {w} " in kept or any(f" {w[:k]}" in kept for k in range(4, min(8, len(w)) + 1)):
                pairs.update(" ".join(words[j : j + 2]) for j in (i - 1, i) if 0 <= j < len(words) - 1)
        (around_bad if y else around_good).update(pairs)
    model.exceptions = tuple(sorted(p for p, n in around_good.items() if n >= least_exception and n > 4 * around_bad[p]))
    machine = model.automaton()
    totals = np.array([model.hits(t, machine) for t in folded])
    lengths = np.array([max(1, t.count(" ") - 1) for t in folded])
    x = np.stack([np.ones(len(totals)), np.log1p(totals), np.log1p(100 * totals / lengths)], 1)
    y, beta, ridge = np.array(marks, float), np.zeros(3), np.diag([1e-3, 0.05, 0.05])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge, x.T @ (y - p) - ridge @ beta)
        beta += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-6:
            break
    model.curve = tuple(float(v) for v in beta)
    return model


def held_out(doc_id="doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, *, max_rows: int = MAX_ROWS, max_text_bytes: int = MAX_TEXT_BYTES) -> ToxicLexicon:
    """Learn from at most ``max_rows`` labelled, not held-out rows, taken by hash of the id, without texts above ``max_text_bytes``."""
    marks = (labels.select(F.col("doc_id").alias("_id"), F.col("toxic").alias("_y")).filter("_id is not null and _y is not null")
             .filter(~held_out("_id")).groupBy("_id").agg(F.max("_y").alias("_y"))
             .orderBy(F.xxhash64("_id"), "_id").limit(max_rows))
    text = F.coalesce(F.col("text"), F.lit(""))
    found = docs.select("doc_id", text.alias("text")).filter(F.octet_length("text") <= max_text_bytes).join(F.broadcast(marks), F.col("doc_id") == F.col("_id"))
    rows = found.groupBy("_id", "_y").agg(F.min("text").alias("text")).toArrow().sort_by("_id")
    return learn(rows.column("text").to_pylist(), [int(v > 0) for v in rows.column("_y").to_pylist()])


def score(docs: DataFrame, model: ToxicLexicon, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, score, predicted of every row."""

    def run(batches):
        machine = model.automaton()
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                scores = []
                for t in part.column("text").to_pylist():
                    folded = fold(t)
                    scores.append(model.score(model.hits(folded, machine), folded.count(" ") - 1))
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(scores, pa.float64()), pa.array([int(s >= threshold) for s in scores], pa.int32())],
                    names=["doc_id", "score", "predicted"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(releasing(run), f"doc_id {kind}, score double, predicted int")


def flag(docs: DataFrame, model: ToxicLexicon, threshold: float = THRESHOLD) -> DataFrame:
    """The rows that are not rejected, all columns, in one narrow pass."""

    def run(batches):
        machine = model.automaton()
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                keep = []
                for t in part.column("text").to_pylist():
                    folded = fold(t)
                    keep.append(model.score(model.hits(folded, machine), folded.count(" ") - 1) < threshold)
                yield part.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(releasing(run), docs.schema)


def op7_toxicity(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", "predicted")


QUERIES = {"op7_toxicity": op7_toxicity}
ORACLES: dict[str, str] = {}
