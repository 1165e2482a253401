"""Global numbering, prefix sums, accumulations over forests and lowest common ancestors."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.scratch import discard, materialize, measured
from . import local

BLOCK = 1 << 12


def width(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def prefix_sum(df: DataFrame, order: list[str], value: str, out: str) -> DataFrame:
    """Exclusive running sum in global order: sums inside range partitions plus offsets of partitions."""
    parts = materialize(df.repartitionByRange(width(df), *order).withColumn("_part", F.spark_partition_id()), "prefix")
    local = F.sum(value).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    sums = parts.groupBy("_part").agg(F.sum(value).alias("_sum"))
    # one row a partition
    offsets = sums.select("_part", F.coalesce(F.sum("_sum").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    return parts.withColumn(out, F.coalesce(local, F.lit(0))).join(F.broadcast(offsets), "_part").withColumn(out, (F.col(out) + F.col("_before")).cast("bigint")).drop("_part", "_before")


def global_index(df: DataFrame, order: list[str], out: str) -> DataFrame:
    """Row numbers from 0 in global order, without a single-partition window."""
    return prefix_sum(df.withColumn("_one", F.lit(1)), order, "_one", out).drop("_one")


def rootfix(forest: DataFrame, value: str, out: str, max_rounds: int = 64) -> DataFrame:
    """Maximum of ``value`` over each vertex and its ancestors, by doubling, in one task below ``local.ROWS``; forest(vid, parent, value)."""
    if forest.count() <= local.ROWS:
        return materialize(local.local_tops(forest.select(F.col("vid").alias("id"), F.col("parent").alias("up"), F.col(value).cast("long").alias("value"))).select(F.col("id").alias("vid"), F.col("most").alias(out)), "rootfix")
    now, seen = measured(forest.select("vid", F.col("parent").alias("up"), F.col(value).alias(out)), "rootfix", open=F.col("up").isNotNull().cast("long"))
    for _ in range(max_rounds):
        if seen["open"] == 0:
            return now.select("vid", out)
        above = now.select(F.col("vid").alias("up"), F.col("up").alias("up2"), F.col(out).alias("more"))
        then, seen = measured(now.join(above, "up", "left").select("vid", F.col("up2").alias("up"), F.greatest(out, "more").alias(out)), "rootfix", open=F.col("up").isNotNull().cast("long"))
        discard(now)
        now = then
    raise RuntimeError("not a forest")


def range_extremes(rows: DataFrame, asked: DataFrame, block: int = BLOCK, name: str = "ranges") -> DataFrame:
    """(id, lo, hi): least lo and greatest hi of rows (idx, lo, hi) over first .. last of questions (id, first, last).

    Rows are numbered without gaps.  A question inside one block of rows is answered there; another
    takes the end of its first block, the start of its last one, and the blocks between, which are
    the rows of a smaller question of the same kind."""
    rows = materialize(rows.select("idx", "lo", "hi"), name)
    n = rows.count()
    if n <= local.ROWS:
        one = lambda df: df.withColumn("block", F.lit(0))
        return local.local_ranges(one(rows), one(asked), "block")
    where = lambda c: F.floor(F.col(c) / block).cast("long")
    rows = rows.withColumn("block", where("idx"))
    asked = materialize(asked.select("id", "first", "last", where("first").alias("block"), where("last").alias("last_block")), f"{name}-asked")
    inside = local.local_ranges(rows, asked.filter("block = last_block"), "block")
    onward, back = Window.partitionBy("block").orderBy("idx"), Window.partitionBy("block").orderBy(F.desc("idx"))
    upto = rows.select(F.col("idx").alias("last"), F.min("lo").over(onward).alias("lo_last"), F.max("hi").over(onward).alias("hi_last"))
    after = rows.select(F.col("idx").alias("first"), F.min("lo").over(back).alias("lo_first"), F.max("hi").over(back).alias("hi_first"))
    wide = asked.filter("block < last_block").join(after, "first").join(upto, "last")
    sums = rows.groupBy(F.col("block").alias("idx")).agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    between = range_extremes(sums, asked.filter("block + 1 < last_block").select("id", (F.col("block") + 1).alias("first"), (F.col("last_block") - 1).alias("last")), block, name)
    met = wide.join(between, "id", "left")
    spanning = met.select("id", F.least("lo_first", "lo_last", "lo").alias("lo"), F.greatest("hi_first", "hi_last", "hi").alias("hi"))
    return inside.unionByName(spanning)


def leaffix(forest: DataFrame, lo: str = "w_lo", hi: str = "w_hi") -> DataFrame:
    """(vid, low, high): minimum of ``lo`` and maximum of ``hi`` over every subtree.

    forest(vid, idx, size, lo, hi): a subtree is a contiguous range of the preorder index."""
    asked = forest.select(F.col("vid").alias("id"), F.col("idx").alias("first"), (F.col("idx") + F.col("size") - 1).alias("last"))
    found = range_extremes(forest.select("idx", F.col(lo).cast("long").alias("lo"), F.col(hi).cast("long").alias("hi")), asked, name="leaffix")
    return found.select(F.col("id").alias("vid"), F.col("lo").alias("low"), F.col("hi").alias("high"))


def lca(forest: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, lca) for pairs (qid, u, v); null across trees or for unknown vertices.

    All vertices strictly after the earlier one, up to the later one, in preorder lie below the
    common ancestor, and one of them is its child: the least parent among them is the answer -
    or the earlier one itself if it holds the later."""
    f = forest.select("vid", "root", "idx", "size", "parent")
    u = f.select(*[F.col(c).alias(f"u_{c}") for c in f.columns])
    v = f.select(*[F.col(c).alias(f"v_{c}") for c in f.columns])
    met = pairs.join(u, pairs["u"] == u["u_vid"], "left").join(v, pairs["v"] == v["v_vid"], "left")
    same = met.filter("u_root = v_root")
    held = same.withColumn("first", F.least("u_idx", "v_idx")).withColumn("last", F.greatest("u_idx", "v_idx"))
    holds = F.when((F.col("u_idx") <= F.col("v_idx")) & (F.col("v_idx") < F.col("u_idx") + F.col("u_size")), F.col("u")).when((F.col("v_idx") <= F.col("u_idx")) & (F.col("u_idx") < F.col("v_idx") + F.col("v_size")), F.col("v"))
    held = materialize(held.withColumn("known", holds).select("qid", "first", "last", "known"), "lca")
    open_ = held.filter("known is null").select(F.col("qid").alias("id"), (F.col("first") + 1).alias("first"), "last")
    above = f.select(F.col("vid").alias("parent"), F.col("idx").alias("pidx"))
    rows = f.join(above, "parent", "left").select("idx", F.coalesce("pidx", "idx").alias("lo"), F.lit(0).cast("long").alias("hi"))
    found = range_extremes(rows, open_, name="lca").select(F.col("id").alias("qid"), F.col("lo").alias("idx")).join(f.select("idx", F.col("vid").alias("found")), "idx").select("qid", "found")
    answer = held.join(found, "qid", "left").select("qid", F.coalesce("known", "found").alias("lca"))
    return pairs.select("qid").join(answer, "qid", "left")
