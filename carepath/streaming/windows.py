"""Event streams: sources, watermarks, windows, sessions, deduplication, joins and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from carepath.sources.tables import SCHEMAS


def read_events(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """Events from a folder of Parquet files, some files per micro-batch; ``ts`` as a timestamp."""
    rows = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def with_lateness(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late)


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    """(start, event_type, n, value); a batch frame gives the same rows."""
    agg = events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("value"))
    return agg.select(F.col("w.start").alias("start"), "event_type", "n", "value")


def hopping(events: DataFrame, size: str = "7 days", step: str = "1 day") -> DataFrame:
    agg = events.groupBy(F.window("ts", size, step).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return agg.select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Sessions of a watermarked stream, given out once no late event can reach them."""
    agg = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.min("event_id").alias("visit_id"), F.min("ts").alias("admit_ts"), F.max("ts").alias("discharge_ts"), F.count("*").alias("n_events"))
    return agg.select(F.col("user_id").alias("subject_id"), "visit_id", "admit_ts", "discharge_ts", "n_events")


def dedup(events: DataFrame) -> DataFrame:
    """Each event id once within the watermark; state is bounded by it."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def enrich(events: DataFrame, customers: DataFrame, nations: DataFrame) -> DataFrame:
    """Stream-static join with the customer's nation."""
    who = customers.join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")
    return events.join(who, F.col("user_id") == F.col("c_custkey")).select("event_id", "ts", "user_id", "event_type", "value", "n_name")


def returns(ends: DataFrame, starts: DataFrame, days: int = 30) -> DataFrame:
    """Stream-stream interval join: a discharge with each admission of the subject in fewer than ``days`` days behind it."""
    a = ends.select(F.col("subject_id").alias("who"), "visit_id", "discharge_ts").withWatermark("discharge_ts", "1 hour")
    b = starts.select("subject_id", F.col("visit_id").alias("next_id"), "admit_ts").withWatermark("admit_ts", "1 hour")
    near = (F.col("admit_ts") > F.col("discharge_ts")) & (F.col("admit_ts") < F.col("discharge_ts") + F.make_dt_interval(days=F.lit(days)))
    return a.join(b, (F.col("who") == F.col("subject_id")) & near).select("subject_id", "visit_id", "next_id")


def score_sink(path: str, score):
    """A foreachBatch function: scores a micro-batch and writes it under its id, so that a repeated batch replaces itself."""

    def write(rows: DataFrame, batch: int) -> None:
        score(rows).write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return write


def start(rows: DataFrame, checkpoint: str, mode: str = "append", to_table: str | None = None, each=None, path: str | None = None) -> StreamingQuery:
    """Run over all that is there, from the checkpoint on: into a memory table, files or a foreachBatch function."""
    writer = rows.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if each is not None:
        return writer.foreachBatch(each).start()
    if path is not None:
        return writer.format("parquet").option("path", path).start()
    return writer.format("memory").queryName(to_table).start()
