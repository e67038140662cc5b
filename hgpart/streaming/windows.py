"""Event streams as pins of window nets, routed by and paired over partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events of Parquet files as they arrive; event time as a timestamp, which watermarks need."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def window_pins(events: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str | None = None, watermark: str | None = "1 hour") -> DataFrame:
    """(start, event_type, user_id, n): pins (window and type) -> user. ``kind``: tumbling, sliding or session (per type and user)."""
    e = events.withWatermark("ts", watermark) if watermark and events.isStreaming else events
    w = F.session_window("ts", size) if kind == "session" else F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
    return e.groupBy(w.alias("w"), "event_type", "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "user_id", "n")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Each event once: within the watermark on a stream, at all on a batch."""
    if events.isStreaming:
        return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def route(events: DataFrame, blocks: DataFrame) -> DataFrame:
    """Events with the block of their user; unknown users have none."""
    return events.join(blocks.select(F.col("node").alias("user_id"), "block"), "user_id", "left")


def pair_events(events: DataFrame, first: str = "view", then: str = "purchase", within: str = "1 hour", watermark: str = "2 hours") -> DataFrame:
    """(user_id, first_id, then_id): pairs of a user's events where the second follows within an interval."""
    e = events.withWatermark("ts", watermark) if events.isStreaming else events
    a = e.filter(F.col("event_type") == first).select(F.col("user_id").alias("ua"), F.col("event_id").alias("first_id"), F.col("ts").alias("ta"))
    b = e.filter(F.col("event_type") == then).select(F.col("user_id").alias("ub"), F.col("event_id").alias("then_id"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"ua = ub and tb > ta and tb <= ta + interval {within}")).select(F.col("ua").alias("user_id"), "first_id", "then_id")
