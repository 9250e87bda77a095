"""DataFrame operators: anchors, and the distributed engine against true cuts."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from balcut.functions import graphs as GR
from balcut.functions import measures as M
from balcut.operators.refine import TooLarge, refine, replay
from balcut.plans.queries import Case
from balcut.schema import PRESETS, Graph, SchemaError, check_graph, check_partition


@pytest.mark.parametrize(("kind", "k", "cut", "positive"), [("chunk", 4, 405, 0), ("chunk", 8, 712, 2), ("round_robin", 4, 2511, 1200), ("round_robin", 8, 2684, 1257)])
def test_anchor_cuts(spark, sf, kind, k, cut, positive):
    c = Case(spark, sf, kind=kind, k=k)
    assert M.cut(c.g.edges, c.p) == cut
    assert M.positive_gain(c.g, c.p).first()["positive"] == positive


def test_degenerate_dense_graph(spark, sf):
    c = Case(spark, sf, "nation_trade", "mod_hash", 5)
    check_graph(c.g)
    check_partition(c.g, c.p, 5)


def test_bad_tables_are_refused(spark):
    nodes = spark.createDataFrame([(1, 1), (2, 1)], "v long, c long")
    with pytest.raises(SchemaError):
        check_graph(Graph(spark.createDataFrame([(2, 1, 1)], "u long, v long, w long"), nodes))
    with pytest.raises(SchemaError):
        check_graph(Graph(spark.createDataFrame([(1, 3, 1)], "u long, v long, w long"), nodes))
    with pytest.raises(SchemaError):
        check_graph(Graph(spark.createDataFrame([(1, 2, "x")], "u long, v long, w string"), nodes))
    g = Graph(spark.createDataFrame([(1, 2, 1)], "u long, v long, w long"), nodes)
    with pytest.raises(SchemaError):
        check_partition(g, spark.createDataFrame([(1, 0)], "v long, b int"), 2)


def test_both_engines(spark, sf):
    c = Case(spark, sf)
    for cfg in (PRESETS["basic_zero"].but(engine="parallel", max_rounds=2), PRESETS["layered"].but(engine="parallel", max_rounds=1, tau=3), PRESETS["packed"].but(engine="replay", max_rounds=4, mu=2)):
        r = refine(c.g, c.p, c.spec, cfg, 3)
        assert M.cut(c.g.edges, r.part) == r.trace["cut_after"] < r.trace["cut_before"] == 2511
        assert M.is_feasible(c.g, r.part, c.spec)


def test_large_graphs_are_not_brought_to_one_task(spark, sf):
    c = Case(spark, sf)
    with pytest.raises(TooLarge):
        replay(c.g, c.p, c.spec, PRESETS["basic"].but(local_edge_limit=10))


def test_components_of_paths(spark):
    edges = spark.createDataFrame([(i, i + 1, 1) for i in range(40) if i % 10 != 9], "u long, v long, w long")
    g = Graph(edges, spark.range(41).select(F.col("id").alias("v"), F.lit(1).cast("long").alias("c")))
    assert {r["v"]: r["comp"] for r in GR.components(g).collect()} == {v: 10 * (v // 10) for v in range(41)}


def test_entry(spark):
    row = __spark_entry__.entry(spark).first()
    assert row["feasible"] and row["cut_after"] < row["cut_before"]


def test_registered_names():
    known, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(sql) <= set(known) and len(known) > 100
