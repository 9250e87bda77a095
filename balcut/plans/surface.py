"""A SQL surface: a graph with a partition as views, and the measures as SQL functions over them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..functions import measures as M
from ..schema import BalanceSpec, Graph

#: Scalar and table functions in SQL, so they are planned and pushed down like any other expression.
FUNCTIONS = (
    "graph_bound(n BIGINT, k INT, num BIGINT, den BIGINT) RETURNS BIGINT RETURN ((den + num) * ((n + k - 1) DIV k)) DIV den",
    "graph_cut_of(pair_a INT, pair_b INT) RETURNS TABLE (cut BIGINT) RETURN SELECT coalesce(sum(w), 0) FROM graph_cut_edges WHERE least(bu, bv) = least(pair_a, pair_b) AND greatest(bu, bv) = greatest(pair_a, pair_b)",
    "graph_arcs_above(gain BIGINT) RETURNS TABLE (a INT, b INT, v BIGINT, g BIGINT) RETURN SELECT x.a, x.b, x.v, x.g FROM graph_gains x WHERE x.g > graph_arcs_above.gain",
)


def register(spark: SparkSession, g: Graph, part: DataFrame, spec: BalanceSpec) -> None:
    """Views graph_edges, graph_nodes, graph_partition, graph_blocks, graph_cut_edges, graph_gains, and the functions over them."""
    views = {"edges": g.edges, "nodes": g.nodes, "partition": part, "blocks": M.blocks(g, part, spec), "cut_edges": M.cut_edges(g.edges, part), "gains": M.gains(M.connections(g.edges, part))}
    for name, df in views.items():
        df.createOrReplaceTempView(f"graph_{name}")
    for made in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {made}")
