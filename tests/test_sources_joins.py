"""Generated graphs, salted joins and balls as clusters against plain counterparts and SQL."""

import duckdb
import pytest

from lwgraph import extras
from lwgraph.operators.joins import salted_join
from lwgraph.sources.edge_source import generated

FOLDER = "/root/testdata/sf0.001"
NAMES = ("d16_ball_clusters", "s7_generated_grid", "s7_grid_components", "j10_salted_join")


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for table in ("lineitem", "supplier", "orders"):
        con.execute(f"create view {table} as select * from '{FOLDER}/{table}.parquet'")
    want = con.execute(extras.ORACLES[name])
    columns = [c[0] for c in want.description]
    got = extras.QUERIES[name](spark, FOLDER)
    assert sorted(got.columns) == sorted(columns)
    assert sorted(tuple(r) for r in got.select(*columns).collect()) == sorted(want.fetchall())


@pytest.mark.parametrize(("kind", "n", "edges"), [("path", 5, 4), ("star", 5, 4), ("clique", 5, 10), ("grid", 3, 12), ("path", 0, 0)])
def test_sizes_of_generated_graphs(spark, kind, n, edges):
    assert generated(spark, kind, n, 3).distinct().count() == edges


def test_salted_left_join_keeps_unmatched_and_null_keys(spark):
    big = spark.createDataFrame([(1, 1), (1, 2), (2, 3), (None, 4)], "k int, row int")
    small = spark.createDataFrame([(1, "a"), (3, "c")], "k int, name string")
    want = sorted(big.join(small, "k", "left").select("row", "name").collect())
    assert sorted(salted_join(big, small, "k", ["row"], 4, "left").select("row", "name").collect()) == want
