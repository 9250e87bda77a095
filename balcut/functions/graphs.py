"""Graph helpers: canonical edges, symmetric view, subgraphs, degrees, components, levels."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import settled


def canonical(pairs: DataFrame, a: str = "u", b: str = "v", w: str | None = "w") -> DataFrame:
    """Edges u < v with summed weights; loops go. Without ``w`` every row weighs 1."""
    weight = F.lit(1).cast("long") if w is None else F.col(w).cast("long")
    rows = pairs.select(F.least(a, b).cast("long").alias("_u"), F.greatest(a, b).cast("long").alias("_v"), weight.alias("_w")).where("_u < _v")
    return rows.groupBy(F.col("_u").alias("u"), F.col("_v").alias("v")).agg(F.sum("_w").alias("w"))


def symmetric(edges: DataFrame) -> DataFrame:
    """(v, nbr, w) in both directions."""
    return edges.select(F.col("u").alias("v"), F.col("v").alias("nbr"), "w").unionByName(edges.select("v", F.col("u").alias("nbr"), "w"))


def neighbour_lists(edges: DataFrame) -> DataFrame:
    return symmetric(edges).groupBy("v").agg(F.array_sort(F.collect_list(F.struct("nbr", "w"))).alias("nbrs"))


def min_weight(edges: DataFrame, least: int) -> DataFrame:
    return edges.where(F.col("w") >= least)


def heaviest(edges: DataFrame, c: int) -> DataFrame:
    """Union over all nodes of their c heaviest edges, ties to smaller ids."""
    top = symmetric(edges).withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("w"), "nbr"))).where(F.col("_r") <= c)
    return top.select(F.least("v", "nbr").alias("u"), F.greatest("v", "nbr").alias("_v"), "w").withColumnRenamed("_v", "v").distinct()


def induced(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    kept = edges.join(nodes.select(F.col("v").alias("u")), "u", "left_semi")
    return kept.join(nodes.select("v"), "v", "left_semi").select("u", "v", "w")


def degrees(g) -> DataFrame:
    """(v, degree, weight); nodes without edges have 0."""
    d = symmetric(g.edges).groupBy("v").agg(F.count("*").alias("degree"), F.sum("w").alias("weight"))
    return g.nodes.select("v").join(d, "v", "left").na.fill(0, ["degree", "weight"])


def triangles(edges: DataFrame) -> DataFrame:
    """(v, n) of nodes in triangles. Edges point from the lesser degree to the greater, so no node has more than sqrt(2 m) of them."""
    degree = symmetric(edges).groupBy("v").agg(F.count("*").alias("d"))
    ends = edges.select("u", "v").join(degree.select(F.col("v").alias("u"), F.col("d").alias("du")), "u").join(degree.withColumnRenamed("d", "dv"), "v")
    low, high = F.struct(F.col("du").alias("d"), F.col("u").alias("v")), F.struct(F.col("dv").alias("d"), F.col("v").alias("v"))
    arcs = ends.select(F.least(low, high).alias("x"), F.greatest(low, high).alias("y"))
    arcs = settled(arcs.select(F.col("x.v").alias("x"), F.col("y.v").alias("y"), F.col("y.d").alias("d")), "arcs")
    z = arcs.select("x", F.col("y").alias("z"), F.col("d").alias("dz"))
    wedges = arcs.join(z, "x").where("struct(d, y) < struct(dz, z)").select("x", "y", "z")
    closed = wedges.join(arcs.select(F.col("x").alias("y"), F.col("y").alias("z")), ["y", "z"], "left_semi")
    return closed.select(F.explode(F.array("x", "y", "z")).alias("v")).groupBy("v").agg(F.count("*").alias("n"))


def isolated(g) -> DataFrame:
    return g.nodes.select("v").join(symmetric(g.edges).select("v"), "v", "left_anti")


def components(g, cut_every: int = 3) -> DataFrame:
    """(v, comp): the smallest node of every node's component, by least labels and label jumps."""
    label = g.nodes.select("v", F.col("v").alias("comp"))
    sym = symmetric(g.edges).select("v", "nbr")
    changed = 1
    while changed:
        old = settled(label, "labels")
        label = old
        for _ in range(cut_every):
            near = sym.join(label.select(F.col("v").alias("nbr"), F.col("comp").alias("m")), "nbr").groupBy("v").agg(F.min("m").alias("m"))
            label = label.join(near, "v", "left").select("v", F.least("comp", F.coalesce("m", "comp")).alias("comp"))
            jump = label.select(F.col("v").alias("comp"), F.col("comp").alias("m"))
            label = label.join(jump, "comp", "left").select("v", F.least("comp", "m").alias("comp"))
        label = settled(label, "labels")
        changed = label.join(old.withColumnRenamed("comp", "before"), "v").where("comp <> before").limit(1).count()
    return label


def levels(edges: DataFrame, roots: DataFrame, depth: int) -> DataFrame:
    """(v, level) of all nodes within ``depth`` steps of the roots."""
    seen = roots.select("v", F.lit(0).alias("level"))
    sym = symmetric(edges).select("v", "nbr")
    front = seen
    for d in range(1, depth + 1):
        near = sym.join(front.select("v"), "v").select(F.col("nbr").alias("v")).distinct()
        front = settled(near.join(seen, "v", "left_anti").select("v", F.lit(d).alias("level")), "front")
        seen = seen.unionByName(front)
    return seen
