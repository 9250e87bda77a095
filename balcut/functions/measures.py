"""Measures of partitions: sizes, cut, gains, and their comparisons. All are single aggregations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import BalanceSpec, Graph
from .graphs import symmetric


def blocks(g: Graph, p: DataFrame, spec: BalanceSpec) -> DataFrame:
    """(b, size, cap, over) of every block, empty ones too."""
    sizes = p.join(g.nodes, "v").groupBy("b").agg(F.sum("c").alias("size"))
    every = p.sparkSession.range(spec.k).select(F.col("id").cast("int").alias("b"))
    size = F.coalesce("size", F.lit(0)).cast("long")
    zero = F.lit(0).cast("long")
    return every.join(sizes, "b", "left").select("b", size.alias("size"), F.greatest(F.lit(spec.lmax) - size, zero).alias("cap"), F.greatest(size - spec.lmax, zero).alias("over"))


def balance(g: Graph, p: DataFrame, spec: BalanceSpec) -> DataFrame:
    """One row: n, lmax, largest block, overload, empty blocks, feasible, imbalance over the average size."""
    mean = -(-spec.n // spec.k)
    return blocks(g, p, spec).agg(
        F.sum("size").alias("n"), F.lit(spec.lmax).cast("long").alias("lmax"), F.max("size").alias("largest"), F.sum("over").alias("overload"),
        F.count_if(F.col("size") == 0).alias("empty"), (F.max("size") <= spec.lmax).alias("feasible"), F.round(F.max("size") / mean - 1, 9).alias("imbalance"),
    )


def is_feasible(g: Graph, p: DataFrame, spec: BalanceSpec) -> bool:
    return bool(balance(g, p, spec).first()["feasible"])


def placed(edges: DataFrame, p: DataFrame) -> DataFrame:
    """Edges with the blocks of both ends, (u, v, w, bu, bv)."""
    return edges.join(p.select(F.col("v").alias("u"), F.col("b").alias("bu")), "u").join(p.select("v", F.col("b").alias("bv")), "v").select("u", "v", "w", "bu", "bv")


def cut_edges(edges: DataFrame, p: DataFrame) -> DataFrame:
    return placed(edges, p).where("bu <> bv")


def cut(edges: DataFrame, p: DataFrame) -> int:
    return cut_edges(edges, p).agg(F.coalesce(F.sum("w"), F.lit(0)).alias("cut")).first()["cut"]


def quotient(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(a, b, w, m): weight and number of edges between blocks a < b."""
    return cut_edges(edges, p).groupBy(F.least("bu", "bv").alias("a"), F.greatest("bu", "bv").alias("b")).agg(F.sum("w").alias("w"), F.count("*").alias("m"))


def connections(edges: DataFrame, p: DataFrame) -> DataFrame:
    """(v, own, b, w): weight from v to every block it touches; tasks send at most one row to a node and block."""
    near = symmetric(edges).join(p.select(F.col("v").alias("nbr"), "b"), "nbr").groupBy("v", "b").agg(F.sum("w").alias("w"))
    return near.join(p.select("v", F.col("b").alias("own")), "v").select("v", "own", "b", "w")


def gains(conn: DataFrame) -> DataFrame:
    """(v, a, b, g): what the cut loses when v goes from its block a to an adjacent block b."""
    inside = F.sum(F.when(F.col("b") == F.col("own"), F.col("w")).otherwise(0)).over(Window.partitionBy("v"))
    return conn.withColumn("_in", inside).where("b <> own").select("v", F.col("own").alias("a"), "b", (F.col("w") - F.col("_in")).alias("g"))


def boundary(conn: DataFrame) -> DataFrame:
    return conn.where("b <> own").select("v").distinct()


def top_gains(gain: DataFrame, c: int = 1) -> DataFrame:
    """The c best nodes of every ordered pair of blocks, ties to smaller ids."""
    r = F.row_number().over(Window.partitionBy("a", "b").orderBy(F.desc("g"), "v"))
    return gain.withColumn("rank", r).where(F.col("rank") <= c).select("a", "b", "rank", "v", "g")


def positive_gain(g: Graph, p: DataFrame) -> DataFrame:
    """One row: nodes on the boundary and nodes with positive gain towards some block."""
    best = gains(connections(g.edges, p)).groupBy("v").agg(F.max("g").alias("g"))
    return best.agg(F.count("*").alias("boundary"), F.count_if(F.col("g") > 0).alias("positive"), F.max("g").alias("best"))


def cut_diff(edges: DataFrame, p: DataFrame, q: DataFrame) -> DataFrame:
    """Edges that are cut in one of two partitions only: (u, v, w, side)."""
    a, b = cut_edges(edges, p).select("u", "v", "w"), cut_edges(edges, q).select("u", "v", "w")
    return a.exceptAll(b).withColumn("side", F.lit("first")).unionByName(b.exceptAll(a).withColumn("side", F.lit("second")))


def overlap(p: DataFrame, q: DataFrame) -> DataFrame:
    """(b1, b2, n): nodes that two partitions put together."""
    return p.select("v", F.col("b").alias("b1")).join(q.select("v", F.col("b").alias("b2")), "v").groupBy("b1", "b2").agg(F.count("*").alias("n"))


def weighted_sizes(g: Graph, p: DataFrame) -> DataFrame:
    return p.join(g.nodes, "v").groupBy("b").agg(F.sum("c").alias("size"))


def apply_moves(p: DataFrame, moves: DataFrame) -> DataFrame:
    """The partition after some moves (v, new_b); a round has at most a model's worth of them."""
    return p.join(F.broadcast(moves.select("v", "new_b")), "v", "left").select("v", F.coalesce("new_b", "b").cast("int").alias("b"))


def apply_delta(conn: DataFrame, edges: DataFrame, moves: DataFrame) -> DataFrame:
    """Connections after moves (v, old_b, new_b): only rows of moved nodes' neighbours change."""
    m = F.broadcast(moves.select(F.col("v").alias("x"), "old_b", "new_b"))
    near = symmetric(edges).join(m, F.col("nbr") == F.col("x")).select("v", "w", "old_b", "new_b")
    delta = near.select("v", F.col("old_b").alias("b"), (-F.col("w")).alias("w")).unionByName(near.select("v", F.col("new_b").alias("b"), "w"))
    touched = F.broadcast(moves.select("v", F.col("new_b").alias("_own")))
    summed = conn.select("v", "b", "w").unionByName(delta).groupBy("v", "b").agg(F.sum("w").alias("w")).where("w <> 0")
    own = conn.select("v", "own").distinct().join(touched, "v", "left").select("v", F.coalesce("_own", "own").cast("int").alias("own"))
    return summed.join(own, "v").select("v", "own", "b", "w")
