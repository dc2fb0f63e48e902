"""Mixing sources to target weights by Pareto order sampling.

Every source gets a target in words. What the target holds of the source's own size in whole is certain: each document
is taken that many times. For the rest, documents are ranked by random odds over inclusion odds, and the first ones
whose sizes fill the remainder are taken once more. The rank is a hash of the document, so reruns agree.

No window ever holds a source: ranks fall into a fixed number of bins, (source, bin) sums are aggregated map-side, and only
documents of the one bin in which a source's remainder ends are ordered exactly.

Defined cases: a null text has size 0; a null source is a source of its own, last; null ids are hashed like any other
value; repeated rows are separate draws (equal ones are ordered by text hash, and which of them is taken leaves the same
rows); an empty table gives an empty mix; a source of size 0 has target 0. DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from carepath.llm._shared import carried, restored, text_of, words_of, written

#: Rank bins; a bin of the largest source holds about a 16,384th of it.
BINS = 16384


def sized(docs: DataFrame, keep: tuple[str, ...] = ("doc_id", "source")) -> DataFrame:
    size = F.size(words_of(text_of())).cast("long")
    return carried(docs, keep, doc_id=F.col("doc_id"), source=F.col("source"), size=size, _text_hash=F.xxhash64(text_of()))


def targets(sizes: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """(source, source_size, target): the weights repeat over the sources in code point order, null last.

    The total is ``share`` of all sizes. A target ends at ``most`` times its source; what it can't take goes to the others
    by weight. Sources reach their ends in the order of end over weight, so running sums in that order give the
    fixed point at once: a source is full when its end is at most its part of what those before it have left.
    """
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    in_order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*(F.lit(float(x)) for x in weights)), (F.row_number().over(in_order) - 1) % len(weights) + 1)
    ends = by_source.select("source", "source_size", w.alias("w"), (F.col("source_size") * F.lit(most)).alias("end"))
    all_rows = Window.partitionBy()
    before = Window.orderBy(F.col("end") / F.col("w"), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    run = ends.select(
        "source", "source_size", "w", "end",
        (F.sum("source_size").over(all_rows) * F.lit(share) - F.coalesce(F.sum("end").over(before), F.lit(0.0))).alias("left"),
        (F.sum("w").over(all_rows) - F.coalesce(F.sum("w").over(before), F.lit(0.0))).alias("w_left"),
    )
    part = F.col("left") / F.col("w_left")
    full = F.col("end") <= F.col("w") * part
    # All sources behind the last full one share one level.
    level = F.min(F.when(~full, F.struct((F.col("end") / F.col("w")).alias("k"), part.alias("part")))).over(all_rows)["part"]
    return run.select("source", "source_size", F.when(full, F.col("end")).otherwise(F.col("w") * level).alias("target"))


def _odds(size: Column) -> Column:
    """Relative inclusion odds: long documents rarely come first, so no single draw swings a source."""
    return F.lit(4096.0) / (F.lit(4096.0) + size)


def uniform(key: Column, seed: int) -> Column:
    """A number between 0 and 1, both left out, from the first 52 bits of an md5 of the key and the seed."""
    text = F.concat(F.coalesce(key.cast("string"), F.lit("null")), F.lit(f"/{seed}"))
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint").cast("double") + 0.5) / float(1 << 52)


def mixed(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0, seed: int = 17, keep: tuple[str, ...] = ("doc_id", "source")) -> DataFrame:
    """``keep`` with size, source_size, target, copies and taken for every document.

    The words taken from a source differ from its target by no more than half the
    document that straddles it.
    """
    sizes = written(sized(docs, keep), "mix-sizes")
    goal = written(targets(sizes, weights, share, most).withColumn("whole", F.least(F.floor(F.col("target") / F.greatest(F.col("source_size"), F.lit(1))), F.lit(int(most)))).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")), "mix-targets")
    u = uniform(F.col("doc_id"), seed)
    f = F.col("rest") / F.greatest(F.col("source_size"), F.lit(1))
    inclusion = F.when((f > 0) & (f < 1), f / (1 - f) * _odds(F.col("size")))
    joined = sizes.join(F.broadcast(goal) if _small(goal) else goal, sizes["source"].eqNullSafe(goal["source"])).drop(goal["source"])
    rank = joined.withColumn("_q", F.when(F.col("size") > 0, (u / (1 - u)) / inclusion))
    binned = rank.withColumn("_bin", F.floor(F.col("_q") / (1 + F.col("_q")) * BINS).cast("int"))
    bins = binned.filter("_bin IS NOT NULL").groupBy("source", "_bin").agg(F.sum("size").alias("in_bin"), F.first("rest").alias("bin_rest"))
    up_to = Window.partitionBy("source").orderBy("_bin")
    edges = bins.withColumn("through", F.sum("in_bin").over(up_to)).filter((F.col("through") >= F.col("bin_rest")) & (F.col("through") - F.col("in_bin") < F.col("bin_rest")))
    edges = edges.select(F.col("source").alias("_s"), F.col("_bin").alias("edge"), (F.col("through") - F.col("in_bin")).alias("already"))
    edge = binned.join(F.broadcast(edges) if _small(goal) else edges, F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s")
    # Exact order within the one bin where a source's remainder ends; the other bins are decided whole.
    inside = F.when(F.col("_bin") == F.col("edge"), F.lit(1)).otherwise(F.lit(0))
    last, other = edge.filter(inside == 1), edge.filter(inside == 0)
    within = Window.partitionBy("source").orderBy("_q", "doc_id", "size", "_text_hash").rowsBetween(Window.unboundedPreceding, 0)
    run = F.col("already") + F.sum("size").over(within)
    last = last.withColumn("_more", (run - F.col("size") / 2.0 <= F.col("rest")).cast("int"))
    other = other.withColumn("_more", F.coalesce((F.col("_bin") < F.col("edge")).cast("int"), F.when(F.col("edge").isNull() & F.col("_q").isNotNull(), 1), F.lit(0)))
    out = last.unionByName(other)
    copies = (F.col("whole") + F.col("_more")).cast("long")
    return restored(out.withColumns({"copies": copies, "taken": copies * F.col("size")}), keep, ["size", "source_size", "target", "copies", "taken"])


#: Sources up to this many are broadcast; beyond, the same join shuffles.
BROADCAST_SOURCES = 100_000


def _small(goal: DataFrame) -> bool:
    return goal.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
