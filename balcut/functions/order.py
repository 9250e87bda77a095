"""Global order without a global sort: ranks and successors over buckets of the order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def ranked(df: DataFrame, bucket: Column, *by: str, name: str = "i") -> DataFrame:
    """Adds the rank (from 0) of each row in the order of (bucket, by).

    Rows are numbered within their bucket; only the table of bucket sizes, one row to a bucket, is
    summed in one place.
    """
    df = df.withColumn("_k", bucket)
    sizes = df.groupBy("_k").agg(F.count("*").alias("_n"))
    before = sizes.select("_k", (F.sum("_n").over(Window.orderBy("_k")) - F.col("_n")).alias("_before"))
    inside = F.row_number().over(Window.partitionBy("_k").orderBy(*by)) - 1
    return df.withColumn("_in", inside).join(before, "_k").withColumn(name, (F.col("_before") + F.col("_in")).cast("long")).drop("_k", "_n", "_before", "_in")


def successors(df: DataFrame, bucket: Column, key: str, *by: str) -> DataFrame:
    """(key, next): every row's successor in the order of (bucket, by)."""
    df = df.select(key, *(c for c in by if c != key)).withColumn("_k", bucket)
    firsts = df.groupBy("_k").agg(F.min_by(key, F.struct(*by)).alias("_first"))
    after = firsts.select("_k", F.lead("_first").over(Window.orderBy("_k")).alias("_after"))
    inner = F.lead(key).over(Window.partitionBy("_k").orderBy(*by))
    return df.withColumn("_next", inner).join(after, "_k").select(key, F.coalesce("_next", "_after").alias("next"))


def by_range(column: str, width: int = 1 << 16) -> Column:
    """Buckets of a whole-number key."""
    return F.floor(F.col(column) / width).cast("long")
