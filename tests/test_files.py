"""Files, SQL surface and triangles against the reference SQL and plain versions."""

import itertools
import random

import duckdb
import pytest

from balcut.functions import graphs as GR
from balcut.plans.queries import QUERIES, SQL
from balcut.sources import files as FI


@pytest.mark.parametrize("name", ["q_triangles", "q_edge_files", "q_partition_files", "q_sql_arcs", "q_sql_functions"])
def test_queries_agree_with_their_sql(spark, sf, name):
    db = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "conversations"):
        db.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    got = QUERIES[name](spark, sf)
    want = db.sql(SQL[name])
    assert sorted(got.columns) == sorted(want.columns)
    order = [got.columns.index(c) for c in want.columns]
    assert sorted(tuple(r[i] for i in order) for r in got.collect()) == sorted(want.fetchall())


def test_triangles(spark):
    r = random.Random(2)
    edges = sorted({tuple(sorted(r.sample(range(30), 2))) for _ in range(150)})
    near = set(edges)
    want = {}
    for t in itertools.combinations(range(30), 3):
        if all(p in near for p in itertools.combinations(t, 2)):
            for v in t:
                want[v] = want.get(v, 0) + 1
    df = spark.createDataFrame([(u, v, 1) for u, v in edges], "u long, v long, w long")
    assert want and {x["v"]: x["n"] for x in GR.triangles(df).collect()} == want
    assert GR.triangles(df.limit(0)).count() == 0


def test_edge_lists_in_any_order(spark, tmp_path):
    (tmp_path / "e.csv").write_text("3,1,2\n1,3,4\n2,2,9\n1,2,1\n")
    assert sorted(FI.read_edges(spark, str(tmp_path / "e.csv"), "csv").collect()) == [(1, 2, 1), (1, 3, 6)]
    (tmp_path / "a.txt").write_text("1 2:1 3:6\n2 1:1\n\n3 1:6\n4\n")
    assert sorted(FI.read_edges(spark, str(tmp_path / "a.txt"), "adjacency").collect()) == [(1, 2, 1), (1, 3, 6)]
    (tmp_path / "bad.csv").write_text("1,x,2\n")
    with pytest.raises(Exception, match="(?i)malformed"):
        FI.read_edges(spark, str(tmp_path / "bad.csv"), "csv").collect()
    with pytest.raises(ValueError, match="unknown format"):
        FI.read_edges(spark, str(tmp_path / "e.csv"), "xml")
