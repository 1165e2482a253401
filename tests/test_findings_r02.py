"""What the findings of a round were about, small enough to fail without a large table."""

import glob
import os

from pyspark.sql import functions as F

from lwgraph import extras, relational
from lwgraph.extras import in_time_order
from lwgraph.operators import connect
from lwgraph.plans.scratch import session_setting

from .test_oracles import brute, graph_of, random_edges

FOLDER = "/root/testdata/sf0.001"


def test_event_files_follow_each_other(spark, tmp_path):
    """By the times of the files, no row of one lies before a row of an earlier one; rows without a time are kept."""
    rows = spark.range(4000).select(F.col("id").alias("event_id"), F.when(F.col("id") != 7, F.timestamp_seconds(F.pmod(F.col("id") * 7919, F.lit(4001)))).cast("timestamp_ntz").alias("ts"))
    in_time_order(rows.repartition(5), str(tmp_path / "files"), most=900)
    files = sorted(glob.glob(str(tmp_path / "files" / "*.parquet")), key=os.path.getmtime)
    spans = [spark.read.parquet(f).agg(F.min("ts"), F.max("ts"), F.count(F.lit(1))).head() for f in files]
    assert len(files) == 5 and sum(s[2] for s in spans) == 4000
    assert all(os.path.getmtime(f) - os.path.getmtime(e) > 1 for e, f in zip(files, files[1:], strict=False))
    assert all(x[1] < y[0] for x, y in zip(spans, spans[1:], strict=False))


def test_small_sets_are_not_estimated_far_off(spark, tmp_path):
    """Nine suppliers a part: one lost to a shared register is more than a tenth."""
    lines = spark.range(18_000).select(F.expr("id div 9").alias("l_partkey"), F.col("id").alias("l_suppkey"))
    lines.write.parquet(str(tmp_path / "lineitem.parquet"))
    assert tuple(relational.q_distinct_error(spark, str(tmp_path)).head()) == (2000, 0)


def test_hops_beyond_the_sessions_row_limit(spark):
    """The rows of two hops are all there where the session allows fewer to a recursion, and its limit stays."""
    want = relational.q_sql_recursive(spark, FOLDER).count()
    with session_setting(spark, "spark.sql.cteRecursionRowLimit", "1000"):
        assert want > 1000 and relational.q_sql_recursive(spark, FOLDER).count() == want
        assert spark.conf.get("spark.sql.cteRecursionRowLimit") == "1000"


def test_union_find_beyond_the_drivers_edges(spark):
    edges, vertices = random_edges(12)
    g, want = graph_of(spark, edges, vertices), brute(edges, vertices)
    for most in (3, 200_000):
        assert {r.vid: r.comp for r in connect.union_find(g, most).collect()} == want["comp"]
