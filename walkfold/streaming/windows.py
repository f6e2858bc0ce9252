"""Windowed relay edges: tumbling, sliding and session windows, for streams and as batch twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A directory of event files as a stream, with a time stamp that watermarks take."""
    rows = spark.readStream.schema(EVENTS.replace("ts timestamp", "ts timestamp_ntz")).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def purchases(events: DataFrame) -> DataFrame:
    return events.where("event_type = 'purchase'").withColumn("ts", F.col("ts").cast("timestamp"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(events: DataFrame, size: str = "1 day", late: str | None = None) -> DataFrame:
    rows = purchases(events)
    rows = rows.withWatermark("ts", late) if late else rows
    return rows.groupBy(F.window("ts", size)).agg(F.count(F.lit(1)).alias("n"), F.min("user_id").alias("least_user")).select(F.unix_micros("window.start").alias("start_us"), "n", "least_user")


def sliding(events: DataFrame, size: str = "2 days", slide: str = "1 day", late: str | None = None) -> DataFrame:
    rows = purchases(events)
    rows = rows.withWatermark("ts", late) if late else rows
    return rows.groupBy(F.window("ts", size, slide)).agg(F.count(F.lit(1)).alias("n")).select(F.unix_micros("window.start").alias("start_us"), "n")


def sessions(events: DataFrame, gap: str = "12 hours", late: str | None = None) -> DataFrame:
    rows = purchases(events)
    rows = rows.withWatermark("ts", late) if late else rows
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")


def last_seen(events: DataFrame) -> DataFrame:
    """A stateful operator: each user's last purchase so far, emitted as it changes."""
    import pandas as pd

    def step(key, batches, state):
        last = state.get[0] if state.exists else -1
        for rows in batches:
            last = max(last, int(rows["us"].max()))
        state.update((last,))
        yield pd.DataFrame({"user_id": [key[0]], "last_us": [last]})

    rows = purchases(events).select("user_id", F.unix_micros("ts").alias("us"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, last_us long", "last long", "update", "NoTimeout")
