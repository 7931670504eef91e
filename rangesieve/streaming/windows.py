"""Filters over event streams: one bucket filter per window of event time, closed by the watermark."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _timed(events: DataFrame, watermark: str) -> DataFrame:
    """Watermarks need timestamps with a zone; tables keep theirs without one."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark) if events.isStreaming else events


def window_filters(events: DataFrame, width: str, slide: str | None, watermark: str, s: int) -> DataFrame:
    """(start, n, codes): the codes user_id * 2^20 + seconds-in-day bucket of every window; works on streams and tables."""
    timed = _timed(events, watermark)
    code = (F.col("user_id") * 2**20 + F.expr(f"(hour(ts) * 3600 + minute(ts) * 60 + second(ts)) div {s}")).alias("z")
    coded = timed.select("ts", code)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return coded.groupBy(window.alias("w")).agg(F.count("*").alias("n"), F.array_sort(F.collect_set("z")).alias("codes")).select(F.col("w.start").alias("start"), "n", "codes")


def session_counts(events: DataFrame, gap: str, watermark: str) -> DataFrame:
    """(user_id, start, n): sessions of a user's events."""
    timed = _timed(events, watermark)
    return timed.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def probe_windows(filters: DataFrame, asked: DataFrame) -> DataFrame:
    """Static questions (start, lo, hi) against closed windows: maybe, by the codes of the window."""
    hit = F.exists("codes", lambda z: (z >= F.col("lo")) & (z <= F.col("hi")))
    return asked.join(filters, "start", "left").select("start", "lo", "hi", F.coalesce(hit, F.lit(False)).alias("maybe"))
