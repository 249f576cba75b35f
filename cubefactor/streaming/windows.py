"""Cells per window from event streams; the same expressions serve batches.

Event times without a zone are read as UTC, since watermarks need zoned times: set the session's time zone to UTC.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def zoned(events: DataFrame, column: str = "ts") -> DataFrame:
    return events.withColumn(column, F.col(column).cast("timestamp"))


def windowed(events: DataFrame, window: Column, keys: list[str], late: str | None = None) -> DataFrame:
    """Count and mean value per window and keys; events later than the watermark are dropped in streams."""
    rows = events.withWatermark("ts", late) if late else events
    return rows.groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"), F.avg("value").alias("mean")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), *keys, "n", "mean")


def tumbling(events: DataFrame, size: str = "1 day", keys: list[str] | None = None, late: str | None = None) -> DataFrame:
    return windowed(events, F.window("ts", size), keys or [], late)


def sliding(events: DataFrame, size: str = "2 days", step: str = "1 day", keys: list[str] | None = None, late: str | None = None) -> DataFrame:
    return windowed(events, F.window("ts", size, step), keys or [], late)


def sessions(events: DataFrame, gap: str = "6 hours", keys: list[str] | None = None, late: str | None = None) -> DataFrame:
    return windowed(events, F.session_window("ts", gap), keys or ["user_id"], late)


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, whatever the source repeats within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def scored(events: DataFrame, factors: list[DataFrame], rank: int) -> DataFrame:
    """A stream of cells (i1..iN, x) joined with static factor slices; slices beyond the broadcast limit are joined by a shuffle."""
    from ..functions.kernels import attach_checked, predict_expr

    names = [f"_f{n}" for n in range(1, len(factors) + 1)]
    return attach_checked(events, factors, "_f", rank, [f.count() for f in factors]).withColumn("prediction", predict_expr(names, rank)).drop(*names)


def read_events(spark, path: str) -> DataFrame:
    """The event table as a stream of its files."""
    schema = spark.read.parquet(path).schema
    return zoned(spark.readStream.schema(schema).parquet(path))
