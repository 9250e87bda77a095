"""Campaigns: what goes to their tasks."""

import tracemalloc

import numpy as np
import pytest

from balcut.operators.local import Local
from balcut.plans import experiments as X

GRID = [("w", g, k, 0.0, 1, "basic:max_rounds=2", "chunk") for g in ("nation_trade", "event_handoff_sparse") for k in (2, 4)]


def test_tasks_get_whole_numbers_only(spark, sf):
    """F2 and the like: names, configurations and starts were strings on every edge of a pandas frame."""
    df = X.campaign(spark, sf, GRID, "improve")
    plan = df._jdf.queryExecution().analyzed().toString()
    assert "MapInArrow" in plan and "FlatMapGroupsInPandas" not in plan
    got = sorted((r["graph"], r["k"], r["config"], r["cut_after"] <= r["cut_before"]) for r in df.collect())
    assert got == sorted((x[1], x[2], x[5], True) for x in GRID)


def test_too_large_graphs_are_refused(spark, sf, monkeypatch):
    monkeypatch.setattr(X, "EDGE_LIMIT", 50)
    with pytest.raises(Exception, match="more than 50 edges"):
        X.campaign(spark, sf, GRID, "improve").collect()


def test_a_graph_in_a_task_takes_narrow_numbers():
    """eight bytes for every place and weight, several times over, took two tasks over their executor's memory."""
    n, k = 100_000, 8
    u, w = np.arange(n - 1), np.ones(n - 1, np.int64)
    tracemalloc.start()
    g = Local(u, u + 1, w, np.arange(n) * k // n, k, -(-n // k))
    held, peak = (x / n for x in tracemalloc.get_traced_memory())
    tracemalloc.stop()
    assert held < 95 and peak < 130, (held, peak)
    assert g.cut() == k - 1 and g.conn.sum() == 2 * (n - 1) and [x for x, _ in g.near(7)] == [8, 6]
    heavy = Local(u[:3], u[:3] + 1, [1 << 40] * 3, [0, 0, 1, 1], 2, 2)
    assert heavy.cut() == 1 << 40 and heavy.conn[1].tolist() == [1 << 40, 1 << 40]


def test_graphs_that_no_task_takes_go_to_the_distributed_engine(spark, sf, monkeypatch):
    """a campaign over a graph of more than the limit had no result."""
    apart, real = [], X.spread_out
    monkeypatch.setattr(X, "EDGE_LIMIT", 100)
    monkeypatch.setattr(X, "spread_out", lambda r, g: apart.append(r["graph"]) or real(r, g))
    grid = [("w", g, 2, 0.0, 1, "packed:max_rounds=1,mu=1,tau=2", "chunk") for g in ("nation_trade", "event_handoff_sparse")]
    rows = {r["graph"]: r for r in X.campaign(spark, sf, grid, "improve", spread=True).collect()}
    monkeypatch.undo()
    for r in X.campaign(spark, sf, grid, "improve").collect():
        got = rows.pop(r["graph"])
        assert (got["cut_before"], got["lmax"]) == (r["cut_before"], r["lmax"])
        assert got["cut_after"] <= got["cut_before"] and got["largest"] <= got["lmax"] and got["overload_after"] == 0
    assert not rows and apart


def test_each_instance_has_its_own_task(spark, sf, monkeypatch):
    """F3 of round 3: bounds from a sample put several instances into one task; the long ones began last."""
    from pyspark.sql import functions as F

    grid = [("w", "nation_trade", k, 0.0, s, "none", "chunk") for k in (2, 3, 4) for s in range(7)]
    got = X.campaign(spark, sf, grid, "improve").select(F.spark_partition_id().alias("task"), "k").orderBy("task").collect()
    assert [r["task"] for r in got] == list(range(21)) and [r["k"] for r in got] == [4] * 7 + [3] * 7 + [2] * 7
