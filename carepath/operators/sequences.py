"""Visit sequences: sliding windows, padding, prefixes, counts, and what is attached to a visit before windowing."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from carepath.operators.temporal import by_subject


def prepare(visits: DataFrame) -> DataFrame:
    """Visits of subjects with several, numbered from 1 in order of admission; ``m`` of them."""
    rows = visits.withColumns({"pos": F.row_number().over(by_subject()), "m": F.count("*").over(Window.partitionBy("subject_id"))})
    return rows.filter("m > 1")


def sliding(visits: DataFrame, k: int, partial: str = "short_only", pad_side: str = "left", last_visit: str = "drop", carry: list[str] | None = None) -> DataFrame:
    """(subject_id, target_visit, visit_ids, mask, n, carried arrays): windows of k visits, oldest first, stride 1.

    With ``last_visit`` "drop" a window's target is the visit behind its end, and the last visit only labels; with "keep"
    it is the window's own last visit. ``short_only`` pads windows only of histories under k, ``all`` also the starts of longer
    ones. ``carry``: columns gathered like the ids (join them on before, so that nothing is shuffled k times).
    """
    w, names = by_subject(), ["visit_id", *(carry or [])]
    frame = w.rowsBetween(-(k - 1), 0)
    rows = visits.withColumns({"_w": F.collect_list(F.struct(*names)).over(frame), "_next": F.lead("visit_id").over(w), "_pos": F.row_number().over(w), "_m": F.count("*").over(Window.partitionBy("subject_id"))})
    if last_visit == "drop":
        rows, usable, target = rows.filter("_next IS NOT NULL"), F.col("_m") - 1, F.col("_next")
    else:
        usable, target = F.col("_m"), F.col("visit_id")
    full = F.col("_pos") >= k
    rows = rows.filter(full if partial == "none" else F.lit(True) if partial == "all" else full | ((usable < k) & (F.col("_pos") == usable)))
    n = F.size("_w")
    gap = F.lit(k) - n

    def padded(name: str):
        own = F.transform("_w", lambda x: x[name])
        element = rows.select(own.alias("o")).schema["o"].dataType.elementType
        empty = F.array_repeat(F.lit(None).cast(element), F.greatest(gap, F.lit(0)))
        return F.concat(empty, own) if pad_side == "left" else F.concat(own, empty)

    on, off = F.array_repeat(F.lit(True), n), F.array_repeat(F.lit(False), gap)
    mask = F.concat(off, on) if pad_side == "left" else F.concat(on, off)
    return rows.select("subject_id", target.alias("target_visit"), padded("visit_id").alias("visit_ids"), mask.alias("mask"), n.alias("n"), *(padded(c).alias(c) for c in carry or []))


def prefixes(visits: DataFrame, max_len: int | None = None, carry: list[str] | None = None) -> DataFrame:
    """(subject_id, target_visit, visit_ids, n, carried arrays): every prefix of a history as a whole, the next visit as target.

    With ``max_len`` only the last ``max_len`` visits of a prefix are kept, and ``n_cut`` tells how many were left out.
    """
    w, names = by_subject(), ["visit_id", *(carry or [])]
    frame = w.rowsBetween(Window.unboundedPreceding if max_len is None else -(max_len - 1), 0)
    rows = visits.withColumns({"_w": F.collect_list(F.struct(*names)).over(frame), "target_visit": F.lead("visit_id").over(w), "_pos": F.row_number().over(w)})
    columns = [F.col("_w").getField(c).alias(c) for c in carry or []]
    cut = [] if max_len is None else [(F.col("_pos") - F.size("_w")).alias("n_cut")]
    return rows.filter("target_visit IS NOT NULL").select("subject_id", "target_visit", F.col("_w").getField("visit_id").alias("visit_ids"), F.size("_w").alias("n"), *cut, *columns)


def sliding_in_tasks(visits: DataFrame, k: int) -> DataFrame:
    """(subject_id, target_visit, visit_ids): the full windows of ``sliding`` built in Arrow tasks, a subject at a time.

    Rows cross to Python once instead of k times; a subject's visits must fit a task.
    """

    def windows(key, table):  # without annotations, which Spark would read as the kind of function
        rows = table.sort_by([("admit_ts", "ascending"), ("visit_id", "ascending")])
        ids = rows.column("visit_id").to_pylist()
        made = [(key[0].as_py(), ids[i + k], ids[i : i + k]) for i in range(len(ids) - k)]
        columns = list(zip(*made, strict=True)) if made else [(), (), ()]
        return pa.table([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.list_(pa.int64()))], names=["subject_id", "target_visit", "visit_ids"])

    rows = visits.select("subject_id", "admit_ts", "visit_id")
    return rows.groupBy("subject_id").applyInArrow(windows, "subject_id long, target_visit long, visit_ids array<long>")


def count_report(visits: DataFrame, ks: tuple[int, ...] = (3, 6)) -> DataFrame:
    """(scheme, samples) in closed form from visits per subject."""
    per = visits.groupBy("subject_id").agg((F.count("*") - 1).alias("m")).filter("m > 0")
    one = per.agg(*(F.sum(F.greatest(F.col("m") - k + 1, F.lit(1))).alias(f"sliding_{k}") for k in ks), F.sum("m").alias("prefixes"), F.sum(F.col("m") * (F.col("m") + 1) / 2).cast("bigint").alias("prefix_cells"))
    return one.unpivot([], one.columns, "scheme", "samples")


def attach(visits: DataFrame, vectors: DataFrame, model_id: str, uses_text: bool = False, pooled: bool = False) -> DataFrame:
    """Visits with the vector ``h`` that the model ``model_id`` gave them; visits without one are left out.

    A model that read text has one vector per chunk and so none per visit, unless chunks were pooled.
    """
    if uses_text and not pooled:
        raise ValueError("a text model has no single vector per visit; pool its chunks first")
    own = vectors.filter(F.col("model_id") == model_id).select("visit_id", "h")
    return visits.join(own, "visit_id")


def attach_multi_hot(visits: DataFrame, sparse: DataFrame) -> DataFrame:
    """Visits with their sparse code ids ``x``; a visit without codes has none of them set."""
    own = sparse.select("visit_id", F.col("ids").alias("x"))
    return visits.join(own, "visit_id", "left").withColumn("x", F.coalesce("x", F.array().cast("array<int>")))
