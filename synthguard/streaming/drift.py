"""Drift of a category's distribution over time, in batch and as a stream."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def daily_drift(events: DataFrame, category: str = "event_type", ts: str = "ts") -> DataFrame:
    """day, n, distance: total variation of each day's distribution to that of all days."""
    counts = events.select(F.date_format(ts, "yyyy-MM-dd").alias("day"), F.col(category).alias("c")).groupBy("day", "c").agg(F.count("*").alias("n"))
    overall = counts.groupBy("c").agg(F.sum("n").alias("q"))  # one row a category
    days = counts.groupBy("day").agg(F.sum("n").alias("total"))
    total = counts.agg(F.sum("n").alias("all"))
    grid = days.crossJoin(F.broadcast(overall)).crossJoin(F.broadcast(total)).join(counts, ["day", "c"], "left")
    return grid.groupBy("day").agg(F.first("total").alias("n"), (0.5 * F.sum(F.abs(F.coalesce("n", F.lit(0)) / F.col("total") - F.col("q") / F.col("all")))).alias("distance"))


def windowed_counts(events: DataFrame, category: str = "event_type", ts: str = "ts", size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Streaming counts by window and category: tumbling, or sliding with slide; events later than `late` are dropped."""
    e = events.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", late)
    w = F.window("_ts", size, slide) if slide else F.window("_ts", size)
    return e.groupBy(w.alias("window"), F.col(category).alias("category")).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, user: str = "user_id", ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Streaming sessions of a user: a gap ends one."""
    e = events.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", late)
    return e.groupBy(F.session_window("_ts", gap).alias("session"), F.col(user).alias("user")).agg(F.count("*").alias("n"))
