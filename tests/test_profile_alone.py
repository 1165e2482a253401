"""A view of its own gets the answers that it has among all views."""

import duckdb
import pytest

from lwgraph import measures, workloads

FOLDER = "/root/testdata/sf0.001"
NAMES = ("c9_component_count", "c9_component_sizes", "c9_connected_pairs", "c9_connected_all_pairs", "t10_same_block", "t11_block_cut_degrees", "t11_block_cut_tree",
         "t12_same_edge_block", "t12_bridge_block_tree", "w_articulation_conversation_chain")


@pytest.fixture
def alone(monkeypatch):
    """Tables of any size count as large, and a pass over all views is an error."""
    monkeypatch.setattr(workloads, "TOGETHER", 0)
    union = workloads.union_of_views

    def of_one(spark, sf_dir, names=workloads.PROFILED):
        assert len(names) == 1
        return union(spark, sf_dir, names)

    monkeypatch.setattr(workloads, "union_of_views", of_one)


@pytest.mark.parametrize("name", NAMES)
def test_query_on_its_own_view(spark, alone, name):
    con = duckdb.connect()
    for table in ("orders", "lineitem", "conversations"):
        con.execute(f"create view {table} as select * from '{FOLDER}/{table}.parquet'")
    every = {**workloads.ORACLES, **measures.ORACLES}
    want = con.execute(every[name])
    columns = [c[0] for c in want.description]
    got = {**workloads.QUERIES, **measures.QUERIES}[name](spark, FOLDER)
    assert sorted(map(str, (tuple(r) for r in got.select(*columns).collect()))) == sorted(map(str, want.fetchall()))
