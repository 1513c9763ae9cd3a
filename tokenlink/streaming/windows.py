"""Time windows and interval joins over encounters; the same functions serve batches and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", size), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str = "12 hours", step: str = "6 hours") -> DataFrame:
    return events.groupBy(F.window("ts", size, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    grouped = events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"), F.max("ts").alias("last"))
    return grouped.select("user_id", F.col("session_window.start").alias("start"), "last", "n")


def notices(events: DataFrame) -> DataFrame:
    return events.where("event_type = 'error'").select(F.col("event_id").alias("notice_id"), F.col("user_id").alias("notice_user"), F.col("ts").alias("notice_ts"))


def seen(events: DataFrame) -> DataFrame:
    return events.where("event_type <> 'error'").select(F.col("event_id").alias("encounter_id"), F.col("user_id").alias("encounter_user"), F.col("ts").alias("encounter_ts"))


def notice_then_encounter(a: DataFrame, b: DataFrame, within: str = "2 days", how: str = "inner") -> DataFrame:
    """Encounters after a notice about the same person, within an interval; watermarks bound the state of a stream."""
    later = (F.col("notice_user") == F.col("encounter_user")) & (F.col("encounter_ts") > F.col("notice_ts")) & (F.col("encounter_ts") <= F.col("notice_ts") + F.expr(f"interval {within}"))
    return a.join(b, later, how).select("notice_id", "encounter_id")
