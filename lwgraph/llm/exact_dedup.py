"""Exact deduplication through content-defined chunk recipes (DataFrame functions only).

Every text is normalised, cut where its content says so (a sentence or line end
beyond a minimum chunk length), and described by the ordered list of its chunk
identifiers.  Chunks cross the network once, collapsed on the map side; documents
travel as recipes from then on.

Identifiers are verified: a 64-bit fingerprint names a chunk only if all chunks that
have it are the same string.  Where they are not, the fingerprint is refined by the
chunk's rank among the strings that share it.

Defined results: a null text counts as empty and all empty texts are equal; a null
doc_id ranks below every id; rows that repeat an id are copies like any other and
share its ``kept`` flag; other columns of the input are ignored, whatever their names;
an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, discard, materialize

MIN_CHUNK, MAX_CHUNK = 512, 2048


def chunk_pattern(min_chunk: int = MIN_CHUNK, max_chunk: int = MAX_CHUNK) -> str:
    return rf"(?s).{{{min_chunk},{max_chunk}}}?(?:[.\n]|\z)|.{{1,{max_chunk}}}"


def _fingerprint(chunk, bits: int):
    whole = F.xxhash64(chunk)
    return whole if bits >= 64 else F.pmod(whole, F.lit(1 << bits))


def _normal(text):
    return ascii_lower(F.coalesce(text, F.lit("")))


def _chunked(docs: DataFrame, min_chunk: int, max_chunk: int) -> DataFrame:
    pattern = F.lit(chunk_pattern(min_chunk, max_chunk))
    return docs.select("doc_id", _normal(F.col("text")).alias("norm")).select(
        "doc_id", "norm", F.regexp_extract_all("norm", pattern, F.lit(0)).alias("chunks"))


def chunk_collisions(chunked: DataFrame, bits: int = 64) -> DataFrame:
    """(fp, chunk, ordinal) of every chunk whose fingerprint also names another string."""
    pieces = chunked.select(F.explode("chunks").alias("chunk"))
    distinct = pieces.select(_fingerprint(F.col("chunk"), bits).alias("fp"), "chunk").distinct()
    # the digest stands for the chunk while strings are only counted
    shared = (distinct.select("fp").groupBy("fp").count().filter("count > 1").select("fp"))
    named = distinct.join(shared, "fp", "left_semi")
    return named.groupBy("fp").agg(F.sort_array(F.collect_set("chunk")).alias("all")) \
        .select("fp", F.posexplode("all").alias("ordinal", "chunk"))


def fingerprint_clashes(chunked: DataFrame, bits: int = 64) -> bool:
    """True when some fingerprint names two strings (verification of all chunks)."""
    pieces = chunked.select(F.explode("chunks").alias("chunk"))
    distinct = pieces.select(_fingerprint(F.col("chunk"), bits).alias("fp"), "chunk").distinct()
    return bool(distinct.select("fp").groupBy("fp").count().filter("count > 1").head(1))


def recipes(docs: DataFrame, *, min_chunk: int = MIN_CHUNK, max_chunk: int = MAX_CHUNK, bits: int = 64) -> DataFrame:
    """(doc_id, recipe, n_chars, text_sha256): the ordered verified chunk identifiers of each row."""
    chunked = _chunked(docs, min_chunk, max_chunk)
    plain = chunked.select(
        "doc_id", F.transform("chunks", lambda c: F.struct(_fingerprint(c, bits).alias("fp"), F.lit(0).alias("ordinal"))).alias("recipe"),
        F.length("norm").alias("n_chars"), F.sha2("norm", 256).alias("text_sha256"))
    if not fingerprint_clashes(chunked, bits):
        return plain
    # A clash: rows are told apart by their digest while the list is taken apart and put together again.
    clashes = chunk_collisions(chunked, bits).select("fp", "chunk", F.col("ordinal").alias("refined"))
    keyed = chunked.withColumn("text_sha256", F.sha2("norm", 256)).select("text_sha256", "chunks").dropDuplicates(["text_sha256"])
    pieces = keyed.select("text_sha256", F.posexplode("chunks").alias("pos", "chunk")).withColumn("fp", _fingerprint(F.col("chunk"), bits))
    refined = (pieces.join(clashes, ["fp", "chunk"], "left")
               .groupBy("text_sha256")
               .agg(F.sort_array(F.collect_list(F.struct("pos", "fp", F.coalesce("refined", F.lit(0)).alias("ordinal")))).alias("parts"))
               .select("text_sha256", F.transform("parts", lambda p: F.struct(p["fp"].alias("fp"), p["ordinal"].alias("ordinal"))).alias("better")))
    return plain.join(refined, "text_sha256", "left").select(
        "doc_id", F.coalesce("better", "recipe").alias("recipe"), "n_chars", "text_sha256")


def exact_groups(docs: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    return _grouped(materialize(recipes(docs, **options), "recipes"))


def _grouped(rows: DataFrame) -> DataFrame:
    groups = (rows.groupBy("recipe", "n_chars")
              .agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"), F.first("text_sha256").alias("sha")))
    # Joined on the digest as a second key, so that both sides are exchanged and a hot
    # group of copies can be split among tasks; equality itself is that of the recipes.
    joined = rows.join(groups.withColumnRenamed("sha", "text_sha256"), ["recipe", "n_chars", "text_sha256"])
    return joined.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that stay, all columns; of rows that share an id and a text one stays."""
    rows = materialize(recipes(docs, **options), "recipes")
    kept = materialize(_grouped(rows).filter("kept").select(F.col("doc_id").alias("_kept_id"), F.col("text_sha256").alias("_kept_sha")), "kept")
    discard(rows)
    # the input's own columns travel in a struct, so that clashing names do no harm
    held = docs.select("doc_id", F.sha2(_normal(F.col("text")), 256).alias("_sha"), F.struct(*docs.columns).alias("_row"))
    found = held.join(kept, held["doc_id"].eqNullSafe(kept["_kept_id"]) & (held["_sha"] == kept["_kept_sha"]), "left_semi")
    return found.dropDuplicates(["doc_id", "_sha"]).select("_row.*")


def op10_exact_dedup(spark, sf_dir):
    return exact_groups(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


SQL = """
with n as (
  select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t
  from documents)
select doc_id, max(doc_id) over (partition by t) as keep_id, count(*) over (partition by t) as group_size,
       doc_id = max(doc_id) over (partition by t) as kept, sha256(t) as text_sha256
from n
"""

QUERIES = {"op10_exact_dedup": op10_exact_dedup}
ORACLES = {"op10_exact_dedup": SQL}
