"""Queries against their SQL on the smallest tables; the driver does the same on larger ones."""

from __future__ import annotations

import pytest

from compare import differs
from joinspace import relops, streams, surfaces, workloads

#: The heavier clustering queries run in test_clustering.
CHEAP = [n for n in workloads.SQL if n.startswith(("size_w9", "size_w4", "count_", "rep_box_w9", "rep_box_w12", "report_box_w12", "value_weights_w12", "class_", "nearest_w12", "kth_", "kmeans1d", "farthest_first_flat", "reduce", "group_", "cost_w9"))]


@pytest.mark.parametrize("name", sorted(surfaces.SQL))
def test_operator(spark, sf, name):
    assert differs(spark, surfaces.QUERIES[name], surfaces.SQL[name], sf) == ""


@pytest.mark.parametrize("name", sorted(CHEAP))
def test_workload(spark, sf, name):
    assert differs(spark, workloads.QUERIES[name], workloads.SQL[name], sf) == ""


@pytest.mark.parametrize("name", ["kcenter_w9_ladder", "kmeans_w9", "sample_w9", "ball_sandwich_w9", "tree_frontier_w9_shrink", "fair_edge_w8", "diversity_edge_w9", "kcenter_w4t_ladder"])
def test_clustering(spark, sf, name):
    assert differs(spark, workloads.QUERIES[name], workloads.SQL[name], sf) == ""


@pytest.mark.parametrize("name", sorted(streams.SQL))
def test_stream(spark, sf, name):
    assert differs(spark, streams.QUERIES[name], streams.SQL[name], sf) == ""


def test_pushdown(spark, sf):
    plan = relops.op_scan_pruned(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan and "l_comment" not in plan


def test_entry_without_llm(spark, monkeypatch):
    """The entry works when the training-data folders are gone."""
    import sys

    import __spark_entry__

    monkeypatch.setitem(sys.modules, "joinspace.llm", None)
    with pytest.raises(ModuleNotFoundError):
        import joinspace.llm  # noqa: F401
    assert not any(n.startswith("op1_") for n in __spark_entry__.queries())


@pytest.mark.parametrize("name", ["op_source_centres", "query_structure"])
def test_tables_are_read(spark, sf, tmp_path, name):
    """Rows that a table gains change the result, which still is that of the SQL."""
    import os

    for f in os.listdir(sf):
        if f != "customer.parquet":
            (tmp_path / f).symlink_to(f"{sf}/{f}")
    rows = spark.read.parquet(f"{sf}/customer.parquet")
    rows.unionByName(rows.limit(7)).coalesce(1).write.parquet(str(tmp_path / "customer.parquet"))
    (query, sql) = next((m.QUERIES[name], m.SQL[name]) for m in (surfaces, workloads) if name in m.SQL)
    assert differs(spark, query, sql, sf) == ""
    assert sorted(query(spark, sf).collect()) != sorted(query(spark, str(tmp_path)).collect())
