"""Start partitions and simple partitioners."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import Graph
from .order import by_range, ranked


def _by_rank(g: Graph, block: Column, order: DataFrame | None, bucket: Column | None, *by: str) -> DataFrame:
    rows = g.nodes.select("v") if order is None else order
    r = ranked(rows, by_range("v") if bucket is None else bucket, *(by or ("v",)))
    return r.select("v", block.cast("int").alias("b"))


def chunk(g: Graph, k: int, n: int, order: DataFrame | None = None, bucket: Column | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """Equal parts in the order of the key, or of the given order."""
    return _by_rank(g, F.floor(F.col("i") * k / F.lit(n)), order, bucket, *by)


def round_robin(g: Graph, k: int, order: DataFrame | None = None, bucket: Column | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    return _by_rank(g, F.col("i") % k, order, bucket, *by)


def mod_hash(g: Graph, k: int) -> DataFrame:
    return g.nodes.select("v", (F.pmod(F.col("v") * 7919 + 13, F.lit(10007)) % k).cast("int").alias("b"))


def skewed(g: Graph, k: int, n: int) -> DataFrame:
    """60 % of the nodes in block 0, the others in turn."""
    r = ranked(g.nodes.select("v"), by_range("v"), "v")
    return r.select("v", F.when(10 * F.col("i") < 6 * F.lit(n), F.lit(0)).otherwise(F.col("i") % k).cast("int").alias("b"))


def random_balanced(g: Graph, k: int, seed: int = 0) -> DataFrame:
    """Perfectly balanced and random: nodes in the order of a seeded hash, in turn."""
    rows = g.nodes.select("v", F.xxhash64("v", F.lit(seed)).alias("h"))
    r = ranked(rows, F.shiftright("h", 48), "h", "v")
    return r.select("v", (F.col("i") % k).cast("int").alias("b"))


def attribute(df: DataFrame, v: str, b: str) -> DataFrame:
    return df.select(F.col(v).cast("long").alias("v"), F.col(b).cast("int").alias("b"))
