"""Event sessions as visits, with real stay lengths; and turns of conversations as visits."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.sources.tables import load


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(subject_id, visit_id, admit_ts, discharge_ts, n_events, value): runs of a user's events with less than ``gap`` in between.

    A window's own end lies ``gap`` behind its last event; discharge is that event.
    """
    win = F.session_window(F.col("ts").cast("timestamp"), gap)
    agg = events.groupBy("user_id", win.alias("w")).agg(F.min("event_id").alias("visit_id"), F.min("ts").alias("admit_ts"), F.max("ts").alias("discharge_ts"), F.count("*").alias("n_events"), F.sum("value").alias("value"))
    return agg.select(F.col("user_id").alias("subject_id"), "visit_id", "admit_ts", "discharge_ts", "n_events", "value")


def session_codes(events: DataFrame, visits: DataFrame) -> DataFrame:
    """(visit_id, code, seq, tie) of the event types inside each session."""
    e = events.select("user_id", "ts", "event_type", "event_id")
    inside = (F.col("ts") >= F.col("admit_ts")) & (F.col("ts") <= F.col("discharge_ts"))
    joined = e.join(visits.select("subject_id", "visit_id", "admit_ts", "discharge_ts"), (F.col("user_id") == F.col("subject_id")) & inside)
    return joined.select("visit_id", F.col("event_type").alias("code"), F.unix_micros(F.col("ts").cast("timestamp")).alias("seq"), F.col("event_id").alias("tie"))


def details(events: DataFrame) -> DataFrame:
    """Events with the key ``k`` of their JSON props."""
    return events.withColumn("k", F.get_json_object("props", "$.k"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(subject_id, visit_id, admit_seq, role, length_class) of conversation turns."""
    c = load(spark, sf_dir, "conversations")
    size = F.length("text")
    return c.select(F.col("conv_id").alias("subject_id"), F.col("turn").alias("visit_id"), F.col("turn").alias("admit_seq"), "role", F.when(size < 100, "short").when(size < 500, "medium").otherwise("long").alias("length_class"))
