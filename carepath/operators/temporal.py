"""Elapsed times, stays, urgent-return labels and their scaling. All share one window, so one shuffle by subject serves them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F


def by_subject() -> WindowSpec:
    return Window.partitionBy("subject_id").orderBy("admit_ts", "visit_id")


def _days(later: Column, earlier: Column) -> Column:
    return F.datediff(F.to_date(later), F.to_date(earlier))


def _clipped(days: Column, negative: str) -> Column:
    return F.when(days < 0, 0).otherwise(days) if negative == "clip" else days


def prior_gap(enc: DataFrame, anchor: str = "discharge", first_fill: int | None = None, negative: str = "clip") -> DataFrame:
    """``gap_days`` since the previous visit's discharge (or admission), and ``has_prior``; a first visit has null or ``first_fill``."""
    before = F.lag(f"{anchor}_ts").over(by_subject())
    gap = _clipped(_days(F.col("admit_ts"), before), negative)
    return enc.withColumns({"gap_days": F.coalesce(gap, F.lit(first_fill)) if first_fill is not None else gap, "has_prior": before.isNotNull()})


def stay_length(enc: DataFrame) -> DataFrame:
    return enc.withColumn("stay_days", _days(F.col("discharge_ts"), F.col("admit_ts")))


def return_label(enc: DataFrame, days: int = 30, direction: str = "forward", anchor: str = "discharge", inclusive: bool = False, urgent=None, strategy: str = "window") -> DataFrame:
    """``y_return``: 1 if a visit follows (forward) or came before (backward) within fewer than ``days`` days.

    ``urgent``: a function of the urgency column that the visit looked at must satisfy. ``strategy`` "range_join" finds forward
    returns by a join on bins of days instead of a window; both give the same rows.
    """
    if strategy == "range_join":
        return _return_by_join(enc, days, anchor, inclusive, urgent)
    w = by_subject()
    if direction == "forward":
        gap, other = _days(F.lead("admit_ts").over(w), F.col(f"{anchor}_ts")), F.lead("urgency").over(w)
    else:
        gap, other = _days(F.col("admit_ts"), F.lag(f"{anchor}_ts").over(w)), F.lag("urgency").over(w)
    near = gap <= days if inclusive else gap < days
    near = near & urgent(other) if urgent else near
    return enc.withColumn("y_return", F.when(near, 1).otherwise(0))


def _return_by_join(enc: DataFrame, days: int, anchor: str, inclusive: bool, urgent) -> DataFrame:
    """Bins as wide as the horizon: a visit looks into those from its admission to its horizon's end."""
    day = lambda c: F.unix_date(F.to_date(c))
    a = enc.withColumn("_bin", F.explode(F.sequence(F.floor(day("admit_ts") / days), F.floor((day(f"{anchor}_ts") + days) / days))))
    b = enc.select(F.col("subject_id").alias("_s"), F.col("visit_id").alias("_v"), F.col("admit_ts").alias("_t"), F.floor(day("admit_ts") / days).alias("_bin"))
    gap = _days(F.col("_t"), F.col(f"{anchor}_ts"))
    after = (F.col("_t") > F.col("admit_ts")) | ((F.col("_t") == F.col("admit_ts")) & (F.col("_v") > F.col("visit_id")))
    hit = a.join(b, (a["_bin"] == b["_bin"]) & (F.col("subject_id") == F.col("_s")) & after & (gap <= days if inclusive else gap < days))
    if urgent:
        raise ValueError("only the next visit's urgency counts; use the window strategy")
    found = hit.select(F.col("visit_id").alias("_hit")).distinct()
    return enc.join(found, F.col("visit_id") == F.col("_hit"), "left").withColumn("y_return", F.col("_hit").isNotNull().cast("int")).drop("_hit")


def lookback_count(enc: DataFrame, days: int) -> DataFrame:
    """Visits of the subject in the ``days`` days up to and with this one's day."""
    w = Window.partitionBy("subject_id").orderBy(F.unix_date(F.to_date("admit_ts"))).rangeBetween(-days, 0)
    return enc.withColumn(f"visits_{days}d", F.count("*").over(w))


@dataclass(frozen=True)
class MinMax:
    """Bounds by column, of the rows they were fitted on."""

    bounds: dict[str, tuple[float, float]]


def fit_minmax(df: DataFrame, cols: list[str], where: Column | None = None) -> MinMax:
    """Two numbers per column; ``where`` limits the fit to the training rows."""
    rows = df.filter(where) if where is not None else df
    got = rows.agg(*(f(c).cast("double").alias(f"{f.__name__}_{c}") for c in cols for f in (F.min, F.max))).first()
    return MinMax({c: (got[f"min_{c}"], got[f"max_{c}"]) for c in cols})


def apply_minmax(df: DataFrame, fit: MinMax, clip: bool = True) -> DataFrame:
    """Columns scaled to [0, 1] beside the old ones, as <name>_scaled; a constant column gives 0, nulls stay null."""

    def scaled(c: str, low: float | None, high: float | None) -> Column:
        if low is None or low == high:
            return F.when(F.col(c).isNotNull(), F.lit(0.0))
        x = (F.col(c) - F.lit(low)) / F.lit(high - low)
        return F.least(F.greatest(x, F.lit(0.0)), F.lit(1.0)) if clip else x

    return df.withColumns({f"{c}_scaled": F.when(F.col(c).isNotNull(), scaled(c, *b)) for c, b in fit.bounds.items()})
