"""Windowed counts and joins of event streams; each works on a batch frame as well."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n_points"), F.approx_count_distinct("user_id").alias("users"))


def sliding(events: DataFrame, width: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return events.groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n_points"))


def session(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """A session is a cloud: points of one user with no longer gap between them."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_points"))


def with_dimension(events: DataFrame, dim: DataFrame, on: str) -> DataFrame:
    """Stream with a static table."""
    return events.join(dim, on, "left")


def within(a: DataFrame, b: DataFrame, by: str, hours: int = 1) -> DataFrame:
    """Stream with stream: rows of ``b`` at most ``hours`` before a row of ``a`` of the same key; both carry a watermark on ts."""
    right = b.select([F.col(c).alias(f"b_{c}") for c in b.columns])
    cond = (F.col(by) == F.col(f"b_{by}")) & (F.col("b_ts") <= F.col("ts")) & (F.col("b_ts") >= F.col("ts") - F.expr(f"INTERVAL {hours} HOURS"))
    return a.join(right, cond)
