"""Joins, ranks and row operations around the methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def visit_codes(visits: DataFrame, codes: DataFrame) -> DataFrame:
    return visits.join(codes, "visit_id")


def attach_notes(visits: DataFrame, notes: DataFrame) -> DataFrame:
    """Visits with their note; ``has_note`` masks the ones without."""
    return visits.join(notes, "visit_id", "left").withColumn("has_note", F.col("note_id").isNotNull())


def reconcile(a: DataFrame, b: DataFrame, key: str, value: str) -> DataFrame:
    """Full outer join of two score sets: which side has a key, and the difference where both do."""
    x, y = a.select(key, F.col(value).alias("left_value")), b.select(key, F.col(value).alias("right_value"))
    side = F.when(F.col("left_value").isNull(), "right").when(F.col("right_value").isNull(), "left").otherwise("both")
    return x.join(y, key, "full").withColumns({"side": side, "difference": F.col("left_value") - F.col("right_value")})


def keep_if(df: DataFrame, other: DataFrame, key: str) -> DataFrame:
    return df.join(other.select(key), key, "left_semi")


def drop_if(df: DataFrame, other: DataFrame, key: str) -> DataFrame:
    return df.join(other.select(key), key, "left_anti")


def asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before its time.

    Both sides are stacked and read once in order of time, right rows first at equal times: no row meets more than one other.
    """
    marks = left.select(by, on, F.lit(1).alias("_side"), F.struct(*left.columns).alias("_l"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    seen = right.select(by, on, F.lit(0).alias("_side"), F.lit(None).cast(marks.schema["_l"].dataType).alias("_l"), F.col(value).alias("_v"))
    w = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = marks.unionByName(seen).withColumn("_v", F.last("_v", ignorenulls=True).over(w))
    return both.filter("_side = 1").select("_l.*", F.col("_v").alias(value))


def in_interval(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, by: str, bin_days: int = 7) -> DataFrame:
    """Points inside spans of the same key: both are put into bins of days, spans into every bin they touch, then compared."""
    bin_of = lambda c: F.floor(F.unix_date(F.to_date(c)) / bin_days)
    p = points.withColumn("_b", bin_of(at))
    s = spans.withColumnRenamed(by, "_by").withColumn("_b", F.explode(F.sequence(bin_of(start), bin_of(end))))
    return p.join(s, (p["_b"] == s["_b"]) & (F.col(by) == F.col("_by")) & (F.col(at) >= F.col(start)) & (F.col(at) <= F.col(end))).drop("_b", "_by")


def grid(a: DataFrame, b: DataFrame) -> DataFrame:
    """All pairs of two short lists, such as thresholds and configurations."""
    return a.crossJoin(F.broadcast(b))


def rank_by(df: DataFrame, by: list[str], order: list[Column | str]) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumns({"row_number": F.row_number().over(w), "rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "decile": F.ntile(10).over(w), "percent_rank": F.percent_rank().over(w), "cume_dist": F.cume_dist().over(w)})


def top_k(df: DataFrame, by: list[Column | str], k: int, per: list[str] | None = None) -> DataFrame:
    """The first k rows, in all or per group; groups are cut before the shuffle already."""
    if not per:
        return df.orderBy(*by).limit(k)
    w = Window.partitionBy(*per).orderBy(*by)
    return df.withColumn("_r", F.row_number().over(w)).filter(F.col("_r") <= k).drop("_r")


def dedupe(df: DataFrame, key: list[str], latest: list[Column | str] | None = None) -> DataFrame:
    """One row per key: any of equal rows, or the first in the order ``latest``."""
    return top_k(df, latest, 1, key) if latest else df.dropDuplicates(key)
