"""Feature vectors of events, in batches and streams: the same functions serve both."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The event types of the table, in the order of the features.
TYPES = ("click", "error", "purchase", "signup", "view")


def _timed(events: DataFrame, late: str | None) -> DataFrame:
    """Streams get a watermark, which needs an instant: times without a zone are in the session's."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if late else events


def tumbling(events: DataFrame, size: str, late: str | None = None) -> DataFrame:
    """Counts and means by window and type; a stream says how late a row may be."""
    return _timed(events, late).groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean"))


def sliding(events: DataFrame, size: str, step: str, late: str | None = None) -> DataFrame:
    return _timed(events, late).groupBy(F.window("ts", size, step), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean"))


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    return _timed(events, late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def without_repeats(events: DataFrame, late: str) -> DataFrame:
    return _timed(events, late).dropDuplicatesWithinWatermark(["event_id"])


def event_features(events: DataFrame, *by: str) -> DataFrame:
    """Six features of each user (and window): counts by type, and the mean value."""
    counts = [F.count(F.when(F.col("event_type") == t, 1)).cast("double").alias(t) for t in TYPES]
    return events.groupBy("user_id", *by).agg(*counts, F.avg("value").alias("mean_value"))


def user_vectors(features: DataFrame) -> DataFrame:
    return features.select(F.col("user_id").alias("vec_id"), F.array(*TYPES, "mean_value").alias("embedding"))
