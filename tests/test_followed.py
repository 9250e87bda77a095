"""Searches that are followed node by node, against whole bands and the counts they must keep."""

import random

import pytest

from balcut.functions import measures as M
from balcut.operators import refine as RF
from balcut.schema import PRESETS, BalanceSpec, Graph, RefineConfig


@pytest.mark.parametrize("tie", ["lex", "hash"])
def test_followed_searches_are_those_of_bands(spark, tie, monkeypatch):
    monkeypatch.setattr(RF, "NEAR_HOPS", 2, raising=False)
    r = random.Random(3)
    n = 60
    edges = {tuple(sorted(r.sample(range(n), 2))): r.randint(1, 3) for _ in range(130)}
    g = Graph(spark.createDataFrame([(*e, w) for e, w in edges.items()], "u long, v long, w long"), spark.createDataFrame([(v, 1) for v in range(n)], "v long, c long"))
    p = spark.createDataFrame([(v, v % 3) for v in range(n)], "v long, b int")
    spec = BalanceSpec.of(3, n)
    engine = RF.Parallel(g, p, spec, RefineConfig(tau=9, mu=1, tie=tie))
    blocked = spark.createDataFrame([(v,) for v in range(0, n, 7)], "v long")
    for shut in (None, blocked):
        seeds = engine.seeds(M.gains(engine.conn), shut, 5)
        ranked = engine.ranks(shut, 5).where("rank = 1").select("a", "b", "v", "g")
        assert sorted(seeds.select("a", "b", "v", "g").collect()) == sorted(ranked.collect())
        found = engine.followed(seeds, shut, 9, 100)
        assert len(found) > 10 and sorted(found) == sorted(tuple(x) for x in engine.banded(seeds, shut, 9, 100).collect())
    monkeypatch.setattr(RF, "NEAR_ROWS", 3)
    assert engine.followed(engine.seeds(M.gains(engine.conn), None, 5), None, 9, 0) is None
    monkeypatch.undo()
    assert engine.round(1) >= 0
    assert sorted(tuple(x) for x in engine.conn.collect()) == sorted(tuple(x) for x in M.connections(g.edges, engine.part).collect())


def test_packed_combination_runs_distributed(spark):
    r = random.Random(4)
    edges = {tuple(sorted(r.sample(range(40), 2))) for _ in range(90)}
    g = Graph(spark.createDataFrame([(a, b, 1) for a, b in edges], "u long, v long, w long"), spark.createDataFrame([(v, 1) for v in range(40)], "v long, c long"))
    p = spark.createDataFrame([(v, v // 10) for v in range(40)], "v long, b int")
    done = RF.Parallel(g, p, BalanceSpec.of(4, 40), PRESETS["packed"].but(max_rounds=1, mu=2, tau=5, combine=True), 1).run()
    assert done.trace["cut_after"] <= done.trace["cut_before"] and done.part.count() == 40
