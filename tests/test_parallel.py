"""The distributed engine against the one-task engine and plain counts: candidates, bands, repair."""

import random

import pytest

from balcut.functions import measures as M
from balcut.operators import refine as RF
from balcut.schema import PRESETS, BalanceSpec, Graph, RefineConfig


def made(spark, n, edges, part, c=1):
    g = Graph(spark.createDataFrame([(min(a, b), max(a, b), 1) for a, b in edges], "u long, v long, w long"), spark.createDataFrame([(v, c) for v in range(n)], "v long, c long"))
    return g, spark.createDataFrame(list(enumerate(part)), "v long, b int")


def test_a_pair_gets_its_33rd_candidate(spark):
    # Pair (0, 1) picks the hub first; it is adjacent to all first candidates of pair (0, 2), not to the last one.
    hub, first, last = 0, list(range(1, 9)), 9
    ones, twos = [10, 11, 12], list(range(13, 24))
    edges = [(hub, x) for x in ones] + [(hub, x) for x in first] + [(x, y) for x in first for y in twos[:6]] + [(last, twos[0])]
    part = [0] * 10 + [1] * 3 + [2] * 11
    g, p = made(spark, 24, edges, part)
    cfg = RefineConfig(model="basic", order="lex", tie="lex")
    engine = RF.Parallel(g, p, BalanceSpec.of(3, 24), cfg)
    got = {(s.a, s.b): s.nodes for s in engine.basic_searches(0, top=2)}
    assert got[0, 1] == [hub] and got[0, 2] == [last] and engine.trace["refills"] > 0
    assert got == {(s.a, s.b): s.nodes for s in engine.basic_searches(0, top=1000)}


def test_a_search_goes_fourteen_hops(spark):
    # A chain in block 0 that only the far end ties to block 1.
    n = 17
    edges = [(i, i + 1) for i in range(n)] + [(0, n), (0, n + 1)]
    g, p = made(spark, n + 2, [e for e in edges if e != (n - 1, n)], [0] * n + [1] * 2)
    engine = RF.Parallel(g, p, BalanceSpec.of(2, n + 2, "0.9"), RefineConfig(mu=1, tau=15, order="lex", tie="lex"))
    far = [s for s in engine.layered_searches(0, 15, 1) if s.a == 0]
    assert far[0].nodes == list(range(15))


@pytest.mark.parametrize("seed", range(3))
def test_repair_makes_any_start_feasible(spark, seed):
    r = random.Random(seed)
    n, k = 30, 4
    edges = {tuple(sorted(r.sample(range(20), 2))) for _ in range(40)}  # the rest is isolated
    part = [0 if r.random() < 0.7 else r.choice([1, 2]) for _ in range(n)]  # block 3 is empty
    g, p = made(spark, n, edges, part)
    spec = BalanceSpec.of(k, n)
    done = RF.Parallel(g, p, spec, PRESETS["basic"].but(max_rounds=1), seed).run()
    assert M.is_feasible(g, done.part, spec) and done.part.count() == n
    over = sum(max(0, part.count(b) - spec.lmax) for b in range(k))
    assert done.trace["repaired"] == over > 0 and done.trace["cut_after"] == M.cut(g.edges, done.part)


def test_what_the_engine_lacks_is_refused(spark):
    g, p = made(spark, 4, [(0, 1), (2, 3)], [0, 0, 1, 1], c=2)
    with pytest.raises(ValueError, match="unit weight"):
        RF.Parallel(g, p, BalanceSpec.of(2, 8), PRESETS["basic"])
    g, p = made(spark, 4, [(0, 1), (2, 3)], [0, 0, 1, 1])
    with pytest.raises(ValueError, match="swap_polish"):
        RF.Parallel(g, p, BalanceSpec.of(2, 4), PRESETS["basic"].but(swap_polish=True))
