"""Readers and writers of graphs and partitions in files: edge lists in four formats, and adjacency lists as text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.graphs import canonical, symmetric

#: Formats of edge lists; all but csv carry their column names.
FORMATS = ("csv", "json", "orc", "parquet")
_EDGE = "u long, v long, w long"


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", schema: str = _EDGE) -> DataFrame:
    """Canonical edges of a list in any order and direction; parallel ones are summed, loops go, a bad row is an error."""
    if kind == "adjacency":
        return read_adjacency(spark, path)
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind}")
    rows = spark.read.schema(schema)
    rows = rows.option("mode", "FAILFAST") if kind in ("csv", "json") else rows
    return canonical(rows.format(kind).load(path))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """Edges of lines ``node neighbour:weight neighbour:weight``. Each edge stands in both of its nodes' lines and counts once."""
    parts = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where(F.trim("value") != "").select(parts[0].cast("long").alias("u"), F.explode(F.slice(parts, 2, F.size(parts))).alias("x"))
    pair = F.split("x", ":")
    return canonical(rows.select("u", pair[0].cast("long").alias("v"), pair[1].cast("long").alias("w")).where("u < v"))


def write_edges(edges: DataFrame, path: str, kind: str = "parquet", buckets: int | None = None) -> None:
    """Write an edge list; ``buckets`` deals the edges by ``u`` over so many files."""
    rows = edges.select("u", "v", "w") if buckets is None else edges.select("u", "v", "w").repartition(buckets, "u")
    if kind == "adjacency":
        near = symmetric(rows).groupBy("v").agg(F.array_sort(F.collect_list(F.struct("nbr", "w"))).alias("nbrs"))
        listed = F.transform("nbrs", lambda x: F.concat_ws(":", x["nbr"].cast("string"), x["w"].cast("string")))
        near.select(F.concat_ws(" ", F.col("v").cast("string"), F.array_join(listed, " ")).alias("value")).write.text(path)
    elif kind in FORMATS:
        rows.write.format(kind).save(path)
    else:
        raise ValueError(f"unknown format {kind}")


def write_partition(part: DataFrame, path: str) -> None:
    """Write (v, b) as one folder a block, so a reader of some blocks skips the others."""
    part.select("v", "b").repartition("b", F.pmod(F.xxhash64("v"), F.lit(16))).write.partitionBy("b").parquet(path)


def read_partition(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("v long, b int").parquet(path)
