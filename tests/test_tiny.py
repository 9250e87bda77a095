"""Queries on tiny graphs and on rules, from given tables."""

import duckdb
import pandas as pd
import pytest

import __spark_entry__


def same(spark, folder, name, *tables):
    con = duckdb.connect()
    for t in tables:
        con.execute(f"create view {t} as select * from '{folder}/{t}.parquet'")
    df = __spark_entry__.queries()[name](spark, str(folder))
    want = con.execute(f"select {', '.join(df.columns)} from ({__spark_entry__.oracle_sql()[name]})").fetchall()
    assert sorted(map(tuple, df.collect()), key=str) == sorted(want, key=str)
    return want


@pytest.mark.parametrize("apart", [False, True])
def test_tiny_optimum_without_edges(spark, tmp_path, apart):
    """the SQL has no sum over no edges; the query gave 0."""
    pd.DataFrame({"s_suppkey": range(12)}).to_parquet(tmp_path / "supplier.parquet")
    pd.DataFrame({"l_orderkey": [1, 1, 2, 2], "l_suppkey": [0, 11, 1, 10 if apart else 2]}).to_parquet(tmp_path / "lineitem.parquet")
    assert same(spark, tmp_path, "q_tiny_optimum", "supplier", "lineitem") == [(None if apart else 0,)]


def test_conflict_kinds_of_orders(spark, tmp_path):
    """the cycles were made up; all three kinds come from lines, each rule by itself."""
    lines = [(1, 2, 0, 1), (2, 3, 1, 2), (2, 3, 5, 1), (3, 0, 1, 3), (4, 1, 0, 1), (4, 2, 0, 1), (5, 4, 3, 0), (6, 6, 0, 2), (6, 7, 5, 2)]
    pd.DataFrame(lines, columns=["l_orderkey", "l_suppkey", "l_partkey", "l_linenumber"]).to_parquet(tmp_path / "lineitem.parquet")
    got = dict(same(spark, tmp_path, "q_conflict_kinds", "lineitem"))
    assert set(got) == {1, 2, 3, 4, 5, 6} and set(got.values()) == {"ok", "repeat", "overload"}


def test_trio_of_nations(spark, sf):
    """the graph was made up on the driver."""
    assert same(spark, sf, "q_trio_optimum", "nation", "lineitem", "orders", "customer", "supplier")[0][0] > 0


def test_search_stays_distributed(spark, sf, monkeypatch):
    """the query brought every edge to one task, which refuses large graphs."""
    from balcut.operators import refine as RF

    monkeypatch.setattr(RF, "in_one_task", None)
    assert len(same(spark, sf, "q_dsearch_tau3", "orders")) == 3


@pytest.mark.parametrize("days", [2, 4])
def test_search_that_ends_early(spark, tmp_path, days):
    """F1 of round 3: the query called the engine's seeds without the gains; a search also ends where its block has no more nodes near."""
    orders = pd.DataFrame({"o_orderkey": range(2 * days), "o_custkey": 0, "o_orderdate": pd.date_range("2024-01-01", periods=2 * days)})
    orders.astype({"o_orderdate": "datetime64[us]"}).to_parquet(tmp_path / "orders.parquet")
    assert len(same(spark, tmp_path, "q_dsearch_tau3", "orders")) == days // 2


def test_two_block_cycles_of_large_graphs(spark, sf, monkeypatch):
    """the query used the one-task engine whatever the graph."""
    from balcut.operators.refine import Parallel, refine
    from balcut.plans.queries import Case
    from balcut.schema import PRESETS

    c = Case(spark, sf, k=2)
    trace = refine(c.g, c.p, c.spec, PRESETS["basic_zero"].but(engine="parallel", max_rounds=2), 1).trace
    assert trace["cycles"] == sum(n for key, n in trace.items() if key.startswith("cycle ")) == trace["cycle any 2"] > 0
    ran = []
    monkeypatch.setitem(PRESETS, "basic_zero", PRESETS["basic_zero"].but(local_edge_limit=10, max_rounds=1))
    monkeypatch.setattr(Parallel, "round", lambda self, salt: ran.append(salt) or 0)
    same(spark, sf, "q_two_block_cycles")
    assert ran
