"""Edge streams: windowed weights of event hand-offs, sessions, late rows, and a live cut."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import scratch_path


def events(spark: SparkSession, sf_dir: str, files: str = "events.parquet") -> DataFrame:
    """The events as a stream, with ``ts`` as an instant: watermarks don't take zone-less times."""
    batch = spark.read.parquet(f"{sf_dir}/{files}")
    first = batch.inputFiles()[0]
    # Streams watch folders: the table's own, or for a single file the one around it.
    single = first.endswith(f"/{files}")
    reader = spark.readStream.schema(batch.schema)
    raw = reader.option("pathGlobFilter", files).parquet(sf_dir) if single else reader.parquet(f"{sf_dir}/{files}")
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_edges(stream: DataFrame, window: str = "1 day", watermark: str = "1 hour") -> DataFrame:
    """(start, user_id, event_type, w): a bipartite edge stream between users and event types, by window."""
    return stream.withWatermark("ts", watermark).groupBy(F.window("ts", window), "user_id", "event_type").agg(F.count("*").alias("w")).select(F.col("window.start").alias("start"), "user_id", "event_type", "w")


def sessions(stream: DataFrame, gap: str = "6 hours", watermark: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n): a user's events without a longer pause."""
    return stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def live_cut(stream: DataFrame, p: DataFrame, window: str = "1 day", watermark: str = "1 hour") -> DataFrame:
    """(start, cut, total): per window the weight that a fixed partition of the users cuts.

    An event is an edge between its user and user (event_id mod users); a stream-static join places both.
    """
    own, other = p.select(F.col("v").alias("user_id"), F.col("b").alias("bu")), p.select(F.col("v").alias("peer"), F.col("b").alias("bv"))
    placed = stream.withWatermark("ts", watermark).join(own, "user_id").join(other, "peer")
    return placed.groupBy(F.window("ts", window)).agg(F.sum((F.col("bu") != F.col("bv")).cast("long")).alias("cut"), F.count("*").alias("total")).select(F.col("window.start").alias("start"), "cut", "total")


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is available into a Parquet sink and give what was written.

    ``append`` gives windows that the watermark has closed; ``complete`` needs a batch sink, so each
    batch replaces the last.
    """
    spark = stream.sparkSession
    out, state = scratch_path(spark, "stream"), scratch_path(spark, "stream-state")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
    else:
        q = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def maintain(stream: DataFrame, p: DataFrame, limit: float, on_drift) -> None:
    """Call ``on_drift(batch_cut, total)`` for each batch whose cut share passes ``limit``."""

    def look(df, _):
        row = df.join(p.select(F.col("v").alias("user_id"), F.col("b").alias("bu")), "user_id").join(p.select(F.col("v").alias("peer"), F.col("b").alias("bv")), "peer").agg(F.count_if(F.col("bu") != F.col("bv")).alias("cut"), F.count("*").alias("n")).first()
        if row["n"] and row["cut"] / row["n"] > limit:
            on_drift(row["cut"], row["n"])

    state = scratch_path(stream.sparkSession, "drift-state")
    stream.writeStream.foreachBatch(look).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
