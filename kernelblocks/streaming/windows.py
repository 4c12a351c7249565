"""Windows over events, the same for a stream and for a table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def watermarked(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Streams get a watermark, for which the time must be an instant; tables stay as they are."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if events.isStreaming else events


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    g = watermarked(events).groupBy(F.window("ts", width).alias("w"), "event_type")
    return g.agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "30 minutes") -> DataFrame:
    g = watermarked(events).groupBy(F.window("ts", width, step).alias("w"))
    return g.agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean")).select(F.col("w.start").alias("start"), "n", "mean")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    g = watermarked(events).groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def progressive_accuracy(scored: DataFrame, width: str = "1 hour") -> DataFrame:
    """Accuracy of predictions by window of their time."""
    hit = (F.col("pred") == F.col("label")).cast("double")
    return watermarked(scored).groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n"), F.avg(hit).alias("accuracy")).select(F.col("w.start").alias("start"), "n", "accuracy")
