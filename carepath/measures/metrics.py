"""Threshold, ranking and loss measures over scores (sample_id, class_id, y, p).

Curves are computed on counts per distinct score, so that what is ordered is the scores, not the cells; with ``bins`` scores
are first rounded to that many steps, which bounds the counts at any number of cells.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from carepath.sources.stores import written

LEAST = 1e-15


def _by(per: list[str] | None) -> list[str]:
    return per or []


def threshold_report(scores: DataFrame, t: float = 0.5, per: list[str] | None = None) -> DataFrame:
    """tp, fp, fn, precision, recall, f1 at p >= t; a measure whose denominator is 0 is 0."""
    hit, true = F.col("p") >= t, F.col("y") == 1
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    counts = scores.groupBy(*_by(per)).agg(n(hit & true).alias("tp"), n(hit & ~true).alias("fp"), n(~hit & true).alias("fn"))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    out = counts.withColumns({"precision": ratio(F.col("tp"), F.col("tp") + F.col("fp")), "recall": ratio(F.col("tp"), F.col("tp") + F.col("fn"))})
    return out.withColumn("f1", ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")))


def macro_threshold(scores: DataFrame, t: float = 0.5, per: list[str] | None = None) -> DataFrame:
    """Means over classes that have a positive."""
    each = threshold_report(scores, t, [*_by(per), "class_id"]).filter(F.col("tp") + F.col("fn") > 0)
    return each.groupBy(*_by(per)).agg(*(F.avg(c).alias(c) for c in ("precision", "recall", "f1")), F.count("*").alias("classes"))


#: Steps of a unit of log odds by which distinct scores are dealt out; some thousand parts from 0 to 1.
STEPS = 64


def curve(scores: DataFrame, per: list[str] | None = None, bins: int | None = None) -> DataFrame:
    """Per distinct score, from the highest on: positives, negatives, and their running sums and totals.

    Scores are dealt by steps of log odds, which keep their order. The steps' sums, a few thousand rows of a group whatever the number of
    scores, become running offsets; scores are ordered within a step only.
    """
    s = F.round(F.col("p") * bins) / bins if bins else F.col("p")
    counts = scores.groupBy(*_by(per), s.alias("p")).agg(F.sum("y").cast("double").alias("pos"), F.sum(1 - F.col("y")).cast("double").alias("neg"))
    inside = F.least(F.greatest(F.col("p"), F.lit(1e-12)), F.lit(1 - 1e-12))
    counts = counts.withColumn("_s", F.floor(F.ln(inside / (1 - inside)) * STEPS))
    steps = counts.groupBy(*_by(per), "_s").agg(F.sum("pos").alias("_p"), F.sum("neg").alias("_n"))
    above = Window.partitionBy(*_by(per)).orderBy(F.desc("_s")).rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy(*_by(per))
    offsets = steps.select(*_by(per), "_s", *(F.coalesce(F.sum(c).over(above), F.lit(0.0)).alias(f"{c}0") for c in ("_p", "_n")), F.sum("_p").over(whole).alias("all_pos"), F.sum("_n").over(whole).alias("all_neg"))
    down = Window.partitionBy(*_by(per), "_s").orderBy(F.desc("p")).rowsBetween(Window.unboundedPreceding, 0)
    rows = counts.join(offsets, [*_by(per), "_s"])
    rows = rows.withColumns({"tp": F.sum("pos").over(down) + F.col("_p0"), "fp": F.sum("neg").over(down) + F.col("_n0")})
    return rows.select(*_by(per), "p", "pos", "neg", "tp", "fp", "all_pos", "all_neg")


def roc_auc(scores: DataFrame, per: list[str] | None = None, bins: int | None = None) -> DataFrame:
    """Share of (positive, negative) pairs in order, ties counting half; null without both."""
    c = curve(scores, per, bins)
    pairs = F.sum(F.col("neg") * (F.col("tp") - F.col("pos") / 2))
    return c.groupBy(*_by(per)).agg((pairs / F.when(F.max("all_pos") * F.max("all_neg") > 0, F.max("all_pos") * F.max("all_neg"))).alias("auc"))


def pr_auc(scores: DataFrame, per: list[str] | None = None, kind: str = "step", bins: int | None = None) -> DataFrame:
    """Area under precision against recall over distinct thresholds: as steps, or as trapezoids from (0, first precision)."""
    c = curve(scores, per, bins).withColumn("prec", F.col("tp") / (F.col("tp") + F.col("fp")))
    if kind == "trapezoid":
        before = F.col("tp") - F.col("pos")
        cells = before + F.col("fp") - F.col("neg")
        c = c.withColumn("prec", (F.col("prec") + F.when(cells > 0, before / cells).otherwise(F.col("prec"))) / 2)
    return c.groupBy(*_by(per)).agg(F.sum(F.col("prec") * F.col("pos") / F.when(F.col("all_pos") > 0, F.col("all_pos"))).alias("aupr"))


def recall_at_precision(scores: DataFrame, level: float = 0.8, per: list[str] | None = None, bins: int | None = None) -> DataFrame:
    """The largest recall over thresholds whose precision is ``level`` or more; 0 if none is."""
    c = curve(scores, per, bins)
    ok = F.col("tp") >= level * (F.col("tp") + F.col("fp"))
    return c.groupBy(*_by(per)).agg(F.coalesce(F.max(F.when(ok, F.col("tp") / F.when(F.col("all_pos") > 0, F.col("all_pos")))), F.lit(0.0)).alias("rp"))


def macro_recall_at_precision(scores: DataFrame, level: float = 0.8, per: list[str] | None = None) -> DataFrame:
    each = recall_at_precision(scores, level, [*_by(per), "class_id"])
    some = scores.groupBy(*_by(per), "class_id").agg(F.max("y").alias("any")).filter("any = 1").drop("any")
    return each.join(some, [*_by(per), "class_id"]).groupBy(*_by(per)).agg(F.avg("rp").alias("rp"))


def recall_at_k(scores: DataFrame, ks: tuple[int, ...] = (10, 20, 30), per: list[str] | None = None, empty: str = "skip") -> DataFrame:
    """Mean over samples of hits among the k best classes over true ones; equal scores go by class id.

    A sample without true classes is left out, or counts 0 with ``empty`` "zero".
    """
    key = [*_by(per), "sample_id"]
    best = Window.partitionBy(*key).orderBy(F.desc("p"), "class_id")
    ranked = scores.withColumn("_r", F.row_number().over(best))
    each = ranked.groupBy(*key).agg(F.sum("y").alias("_t"), *(F.sum(F.when(F.col("_r") <= k, F.col("y")).otherwise(0)).alias(f"_h{k}") for k in ks))
    return _mean_recall(each, ks, per, empty)


def _mean_recall(each: DataFrame, ks: tuple[int, ...], per: list[str] | None, empty: str) -> DataFrame:
    share = lambda k: F.col(f"_h{k}") / F.when(F.col("_t") > 0, F.col("_t"))
    value = (lambda k: F.coalesce(share(k), F.lit(0.0))) if empty == "zero" else share
    return each.groupBy(*_by(per)).agg(*(F.avg(value(k)).alias(f"recall_{k}") for k in ks))


def recall_at_k_arrays(rows: DataFrame, ks: tuple[int, ...] = (10, 20, 30), per: list[str] | None = None, empty: str = "skip") -> DataFrame:
    """The same from one row per sample: scores ``p`` by class and true class numbers ``y``. Nothing is exploded or shuffled."""
    order = F.array_sort(F.transform("p", lambda x, i: F.struct((-x).alias("s"), i.alias("i"))))
    top = rows.withColumns({"_o": F.transform(order, lambda x: x["i"]), "_t": F.size(F.array_distinct("y"))})
    each = top.withColumns({f"_h{k}": F.size(F.array_intersect(F.slice("_o", 1, k), "y")) for k in ks})
    return _mean_recall(each, ks, per, empty)


def bce(scores: DataFrame, per: list[str] | None = None) -> DataFrame:
    """Binary cross entropy, the mean over cells, logarithms clipped."""
    p = F.least(F.greatest(F.col("p"), F.lit(LEAST)), F.lit(1 - LEAST))
    return scores.groupBy(*_by(per)).agg(F.avg(-(F.col("y") * F.ln(p) + (1 - F.col("y")) * F.ln(1 - p))).alias("bce"))


def ce(scores: DataFrame, per: list[str] | None = None) -> DataFrame:
    """Cross entropy of exclusive classes: the mean over samples of the summed cells."""
    p = F.greatest(F.col("p"), F.lit(LEAST))
    return scores.groupBy(*_by(per)).agg((F.sum(-F.col("y") * F.ln(p)) / F.countDistinct("sample_id")).alias("ce"))


def over_folds(rows: DataFrame, config: str, measures: list[str]) -> DataFrame:
    """Mean and standard deviation of the measures over folds, per configuration."""
    return rows.groupBy(config).agg(*(f(m).alias(f"{m}_{n}") for m in measures for f, n in ((F.avg, "mean"), (F.stddev_samp, "std"))), F.count("*").alias("folds"))


def compare(runs: DataFrame, config: str, base: str, measures: list[str]) -> DataFrame:
    """Each configuration against ``base``: differences in percentage points and in per cent of the base; null per cent where the base is 0."""
    b = runs.filter(F.col(config) == base).select(*(F.col(m).alias(f"_{m}") for m in measures))
    joined = runs.crossJoin(F.broadcast(b))
    points = {f"{m}_points": (F.col(m) - F.col(f"_{m}")) * 100 for m in measures}
    per_cent = {f"{m}_percent": (F.try_divide(m, f"_{m}") - 1) * 100 for m in measures}
    return joined.select(config, *(c.alias(n) for n, c in {**points, **per_cent}.items()))


def as_table(long: DataFrame, row: str, column: str, value: str, names: list[str]) -> DataFrame:
    """A results table: one row per ``row``, one column per name."""
    return long.groupBy(row).pivot(column, names).agg(F.first(value))


def suite(scores: DataFrame, task: str = "binary", ks: tuple[int, ...] = (10, 20, 30), threshold: float = 0.5, level: float = 0.8, average: str = "micro", empty: str = "skip", per: list[str] | None = None) -> DataFrame:
    """All measures of a task in one row (or one per group)."""
    if average == "macro":
        out = [macro_threshold(scores, threshold, per), macro_recall_at_precision(scores, level, per), pr_auc(scores, per)]
    else:
        out = [threshold_report(scores, threshold, per), recall_at_precision(scores, level, per), pr_auc(scores, per)]
    out.append(roc_auc(scores, per) if task == "binary" else recall_at_k(scores, ks, per, empty))
    first, *rest = out
    for r in rest:
        first = first.join(r, per) if per else first.crossJoin(r)
    return first


#: Steps of a unit of log odds by which packed scores are dealt.
PACK_STEPS = 8
#: Cells that a task holds, of all rotations, before it packs them.
PACK_CELLS = 1 << 20


def _packs(ks: tuple[int, ...], threshold: float):
    """Sums of each rotation (step null) and its distinct scores with their positives and negatives, packed by steps of log odds."""
    edges = 1 / (1 + np.exp(-np.arange(-28 * PACK_STEPS, 28 * PACK_STEPS + 1) / PACK_STEPS))
    names = ["rotation", "step", "p", "pos", "neg", "n_pos", "n_neg", "tp", "fp", "fn", "some", "shares"]
    kinds = [pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.float64())]

    def packed(rotation: int, p: np.ndarray, y: np.ndarray) -> pa.RecordBatch:
        hit, true = p >= threshold, y.sum(axis=1)
        own, shares = true > 0, []
        if ks:
            best = np.argsort(-p[own], axis=1, kind="stable")  # equal scores go by class
            shares = [float((np.take_along_axis(y[own], best[:, :k], axis=1).sum(axis=1) / true[own]).sum()) for k in ks]
        rows = [[rotation, None, None, None, None, 0, 0, int((hit & y).sum()), int((hit & ~y).sum()), int((~hit & y).sum()), int(own.sum()), shares]]
        values, at = np.unique(p.ravel(), return_inverse=True)
        every = np.bincount(at)
        pos = np.bincount(at, weights=y.ravel()).astype(np.int32)
        neg = (every - pos).astype(np.int32)
        step = np.searchsorted(edges, values, "right")
        cuts = np.flatnonzero(np.diff(step, prepend=-1))
        for a, b in zip(cuts, np.append(cuts[1:], len(step)), strict=True):
            rows.append([rotation, int(step[a]), values[a:b].tobytes(), pos[a:b].tobytes(), neg[a:b].tobytes(), int(pos[a:b].sum()), int(neg[a:b].sum()), 0, 0, 0, 0, None])
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        cells = 0

        def given(rotation: int) -> pa.RecordBatch:
            p, y = (np.concatenate(c) for c in zip(*held.pop(rotation), strict=True))
            return packed(rotation, p, y)

        for batch in batches:
            if not batch.num_rows:
                continue
            rotations = batch.column(0).to_numpy()
            width = batch.column(3).flatten()
            p = width.to_numpy().reshape(batch.num_rows, -1)
            y, lists = np.zeros(p.shape, bool), batch.column(2)
            y[np.repeat(np.arange(len(p)), np.diff(lists.offsets.to_numpy())), lists.flatten().to_numpy()] = True
            for r in np.unique(rotations).tolist():
                of = rotations == r
                held.setdefault(r, []).append((p[of], y[of]))
            cells += p.size
            if cells >= PACK_CELLS:
                cells = 0
                for r in sorted(held):
                    yield given(r)
        for r in sorted(held):
            yield given(r)

    return run, "rotation int, step int, p binary, pos binary, neg binary, n_pos long, n_neg long, tp long, fp long, fn long, some long, shares array<double>"


def _areas(level: float):
    """Of one step of one rotation: its parts of both areas and the largest recall at ``level``."""

    def run(key, table):
        read = lambda c, kind: np.frombuffer(b"".join(table.column(c).to_pylist()), kind)
        first = {c: float(table.column(c)[0].as_py()) for c in ("_p0", "_n0", "all_pos", "all_neg")}
        values, at = np.unique(read("p", np.float64), return_inverse=True)
        pos, neg = (np.bincount(at, weights=read(c, np.int32))[::-1] for c in ("pos", "neg"))
        tp, fp = np.cumsum(pos) + first["_p0"], np.cumsum(neg) + first["_n0"]
        area = float((tp / (tp + fp) * pos).sum())
        pairs = float((neg * (tp - pos / 2)).sum())
        ok = tp >= level * (tp + fp)
        return pa.table({"rotation": pa.array([key[0].as_py()], pa.int32()), "area": [area], "pairs": [pairs], "most": [float(tp[ok].max()) if ok.any() else 0.0], "all_pos": [first["all_pos"]], "all_neg": [first["all_neg"]]})

    return run, "rotation int, area double, pairs double, most double, all_pos double, all_neg double"


def suite_arrays(rows: DataFrame, task: str = "binary", ks: tuple[int, ...] = (10, 20, 30), threshold: float = 0.5, level: float = 0.8) -> DataFrame:
    """``suite`` per rotation from one row per sample: (rotation, sample_id, y, p) with true classes and the scores of all classes.

    What adds up is summed where the scores are. For the curves, scores are dealt as packs by steps of log odds; a step is ordered in a task.
    """
    ks = ks if task != "binary" else ()
    run, schema = _packs(ks, threshold)
    packs = written(rows.select("rotation", "sample_id", "y", "p").mapInArrow(run, schema))
    sums = packs.filter("step IS NULL").groupBy("rotation").agg(*(F.sum(c).alias(c) for c in ("tp", "fp", "fn", "some")), *(F.sum(F.col("shares")[i]).alias(f"_h{k}") for i, k in enumerate(ks)))
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    sums = sums.withColumns({"precision": ratio(F.col("tp"), F.col("tp") + F.col("fp")), "recall": ratio(F.col("tp"), F.col("tp") + F.col("fn")), "f1": ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn"))})
    steps = packs.filter("step IS NOT NULL").groupBy("rotation", "step").agg(F.sum("n_pos").alias("_p"), F.sum("n_neg").alias("_n"))
    above, every = Window.partitionBy("rotation").orderBy(F.desc("step")).rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy("rotation")
    offsets = steps.select("rotation", "step", *(F.coalesce(F.sum(c).over(above), F.lit(0)).alias(f"{c}0") for c in ("_p", "_n")), F.sum("_p").over(every).alias("all_pos"), F.sum("_n").over(every).alias("all_neg"))
    areas, kinds = _areas(level)
    dealt = packs.filter("step IS NOT NULL").select("rotation", "step", "p", "pos", "neg").join(F.broadcast(offsets), ["rotation", "step"])
    each = dealt.groupBy("rotation", "step").applyInArrow(areas, kinds).groupBy("rotation").agg(F.sum("area").alias("area"), F.sum("pairs").alias("pairs"), F.max("most").alias("most"), F.max("all_pos").alias("all_pos"), F.max("all_neg").alias("all_neg"))
    share = lambda v, n: F.col(v) / F.when(n > 0, n)
    found = each.select("rotation", F.coalesce(share("most", F.col("all_pos")), F.lit(0.0)).alias("rp"), share("area", F.col("all_pos")).alias("aupr"), share("pairs", F.col("all_pos") * F.col("all_neg")).alias("auc"))
    last = ["auc"] if task == "binary" else [F.try_divide(f"_h{k}", "some").alias(f"recall_{k}") for k in ks]
    return sums.join(found, "rotation").select("rotation", "tp", "fp", "fn", "precision", "recall", "f1", "rp", "aupr", *last)


def is_calibrated(scores: DataFrame, bins: int = 10) -> DataFrame:
    """Mean score and share of positives by tenth of the score."""
    b: Column = F.least(F.floor(F.col("p") * bins), F.lit(bins - 1)).cast("int")
    return scores.groupBy(b.alias("bin")).agg(F.avg("p").alias("mean_p"), F.avg("y").alias("share"), F.count("*").alias("cells"))
