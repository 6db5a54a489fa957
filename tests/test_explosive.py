"""The queries on the explosive join, bound to a small one."""

from __future__ import annotations

from joinspace import workloads


def test_explosive_query_builds_a_coreset(spark, sf, monkeypatch):
    """Bound to the small w9: the query solves on a coreset, and an estimate that leaves tuples out is not accepted."""
    bind, solve, traces = workloads.bind, workloads.kcenter.coreset_solve, []

    def traced(*a, **b):
        traces.append(solve(*a, **b))
        return traces[-1]

    monkeypatch.setattr(workloads, "bind", lambda spark, sf, w, **b: bind(spark, sf, "w9", **b))
    monkeypatch.setattr(workloads.kcenter, "coreset_solve", traced)
    assert workloads.QUERIES["kcenter_w3_coreset"](spark, sf).first()["finite"]
    assert len(traces) == 1 and traces[0].trace["coreset"] > 0
    monkeypatch.setattr(workloads.kcenter, "coreset_solve", lambda *a, **b: workloads.kcenter.Solution(traces[0].centres, traces[0].estimate / 100))
    assert not workloads.QUERIES["kcenter_w3_coreset"](spark, sf).first()["finite"]
