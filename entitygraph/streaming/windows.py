"""Windowed counts, repeats and interval joins over a stream of events, read from files and written as Parquet."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.shared import new_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table's files as a stream; ts as an instant, which watermarks need."""
    return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Reads all that is there now and gives what was written. Append goes to the file sink, which commits each batch once; complete results replace the last ones."""
    spark, path = stream.sparkSession, new_path(stream.sparkSession, "stream")
    writer = stream.writeStream.trigger(availableNow=True).outputMode(mode).option("checkpointLocation", new_path(spark, "stream-state"))
    if mode == "append":
        query = writer.format("parquet").option("path", path).start()
    else:
        query = writer.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(path)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def _windowed(events: DataFrame, window: Callable) -> DataFrame:
    counted = events.groupBy(window(F.col("ts")).alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum(F.col("value").cast("decimal(18,2)")), 2).cast("double").alias("total"))
    stamp = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return counted.select(stamp(F.col("w.start")).alias("from_ts"), stamp(F.col("w.end")).alias("to_ts"), "event_type", "n", "total")


def tumbling(events: DataFrame) -> DataFrame:
    return _windowed(events, lambda t: F.window(t, "1 hour"))


def sliding(events: DataFrame) -> DataFrame:
    return _windowed(events, lambda t: F.window(t, "1 hour", "30 minutes"))


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    """Of each user, runs of events with no gap as long as that: from the first, and how many."""
    counted = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return counted.select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("from_ts"), "n")


def first_of_kind(events: DataFrame, delay: str = "60 days") -> DataFrame:
    """The first event that arrives of each user and kind, state being kept for the watermark's delay."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def followed_within(events: DataFrame, first: str, second: str, minutes: int, delay: str = "1 hour") -> DataFrame:
    """Pairs of a user's events of two kinds, the second at most so many minutes after the first: both sides keep state only as long as a match can come."""
    one = events.withWatermark("ts", delay)
    left = one.where(F.col("event_type") == first).select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    right = one.where(F.col("event_type") == second).select(F.col("user_id").alias("user_b"), F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    near = F.expr(f"user_id = user_b AND tb >= ta AND tb <= ta + INTERVAL {minutes} MINUTES")
    return left.join(right, near).select("user_id", "a", "b")
