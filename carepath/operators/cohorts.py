"""Cohorts: profiles, patient labels, the return dataset and the next-codes dataset."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from carepath.operators import codes as C
from carepath.operators import temporal


def profile(labelled: DataFrame) -> DataFrame:
    """One row: subjects, ever positive and never, with one and several visits, visits, and visits per subject."""
    per = labelled.groupBy("subject_id").agg(F.count("*").alias("v"), F.max("y_return").alias("y"))
    return per.agg(
        F.count("*").alias("patients"), F.sum("y").cast("bigint").alias("positive"), F.sum(1 - F.col("y")).cast("bigint").alias("negative"),
        F.sum((F.col("v") == 1).cast("int")).alias("single_visit"), F.sum((F.col("v") > 1).cast("int")).alias("multi_visit"),
        F.sum("v").alias("visits"), F.min("v").alias("min_visits"), F.percentile("v", F.lit(0.5)).alias("median_visits"), F.max("v").alias("max_visits"),
    )


def patient_label(labelled: DataFrame) -> DataFrame:
    return labelled.groupBy("subject_id").agg(F.max("y_return").alias("y_patient"))


def return_dataset(enc: DataFrame, days: int = 30, direction: str = "forward", anchor: str = "discharge", censor_days: int | None = None) -> DataFrame:
    """All visits with gap, stay and label; ``censor_days`` drops those whose horizon ends behind the data."""
    rows = temporal.return_label(temporal.stay_length(temporal.prior_gap(enc)), days, direction, anchor)
    if censor_days is None:
        return rows
    end = enc.agg(F.max("admit_ts").alias("_end"))
    inside = F.date_add(F.to_date("discharge_ts"), censor_days) <= F.to_date("_end")
    return rows.join(F.broadcast(end)).filter(inside).drop("_end")


def next_codes_label(visits: DataFrame, lists: DataFrame, require_label_codes: bool = True) -> DataFrame:
    """Visits with their own codes and, as ``next_codes``, those of the subject's next visit; last visits are left out.

    ``lists``: (visit_id, codes). The label stays sparse; a next visit without codes ends the row unless allowed.
    """
    rows = visits.join(lists.select("visit_id", "codes"), "visit_id", "left").withColumn("codes", F.coalesce("codes", F.array().cast("array<string>")))
    w = temporal.by_subject()
    rows = rows.withColumns({"next_visit": F.lead("visit_id").over(w), "next_codes": F.lead("codes").over(w)}).filter("next_visit IS NOT NULL")
    return rows.filter(F.size("next_codes") > 0) if require_label_codes else rows


def next_dx_dataset(enc: DataFrame, lists: DataFrame, require_label_codes: bool = True) -> DataFrame:
    """Visits of subjects with several, each with gap, stay, own and next codes: one window serves them all."""
    return next_codes_label(temporal.stay_length(temporal.prior_gap(enc)), lists, require_label_codes)


def as_ids(dataset: DataFrame, vocab: DataFrame) -> DataFrame:
    """(visit_id, next_visit, x, y): sparse vocabulary ids of own and next codes."""
    x = C.ids(dataset.select("visit_id", "codes"), vocab).withColumnRenamed("ids", "x")
    y = C.ids(dataset.select("visit_id", F.col("next_codes").alias("codes")), vocab).withColumnRenamed("ids", "y")
    return dataset.select("subject_id", "visit_id", "next_visit", "gap_days", "stay_days").join(x, "visit_id").join(y, "visit_id")


def carried_over(dataset: DataFrame) -> DataFrame:
    """Share of next codes that the current visit has, per visit: what a persistence scorer can reach."""
    n = F.size(F.array_distinct("next_codes"))
    return dataset.select("visit_id", F.size(F.array_intersect("codes", "next_codes")).alias("kept"), n.alias("n_next"), (F.size(F.array_intersect("codes", "next_codes")) / n).alias("share"))


def last_visits(enc: DataFrame) -> DataFrame:
    """Each subject's last visit, which has no observed future."""
    w = Window.partitionBy("subject_id").orderBy(F.desc("admit_ts"), F.desc("visit_id"))
    return enc.withColumn("_r", F.row_number().over(w)).filter("_r = 1").drop("_r")
