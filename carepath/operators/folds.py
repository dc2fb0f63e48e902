"""Folds, rotations, balancing and audits. Order comes from hashes of keys, never from random numbers, so it is the same on any cluster."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from carepath.sources.stores import written

#: Hash prefixes for exact ranks: 1,024 buckets of 2^22, so that a stratum is ranked in as many tasks.
BUCKET = 1 << 22


def hashed(*key: str | Column, seed: int | str | Column = 42) -> Column:
    """The first 32 bits of an md5 of the key and the seed."""
    parts = [F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in key]
    mark = seed if isinstance(seed, Column) else F.lit(str(seed))
    return F.conv(F.substring(F.md5(F.concat_ws("/", *parts, mark)), 1, 8), 16, 10).cast("bigint")


def uniform(*key: str | Column, seed: int | str | Column = 42) -> Column:
    return hashed(*key, seed=seed) / float(1 << 32)


def ranked(df: DataFrame, key: str, strata: list[str], seed: int | str | Column = 42) -> DataFrame:
    """``rank``: 1, 2, … in hash order within a stratum, without bringing a stratum to one task.

    Hash prefixes part a stratum into buckets; their counts, a few rows, become running offsets; rows are numbered within
    their bucket only. The offsets are joined on what the rows are then dealt by, so the join adds no exchange.
    """
    rows = df.withColumn("_h", hashed(key, seed=seed)).withColumn("_b", F.floor(F.col("_h") / BUCKET))
    counts = rows.groupBy(*strata, "_b").agg(F.count("*").alias("_n"))
    before = Window.partitionBy(*strata).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("_o", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    own = Window.partitionBy(*strata, "_b").orderBy("_h", key)
    return rows.join(offsets, [*strata, "_b"]).withColumn("rank", F.row_number().over(own) + F.col("_o")).drop("_h", "_b", "_o")


def by_subject(patients: DataFrame, n: int = 10, strata: str = "y_patient", seed: int = 42, method: str = "exact") -> DataFrame:
    """(subject_id, stratum, fold): folds of whole patients with the same mix of strata; ``hash`` is even only on average."""
    rows = patients.select("subject_id", F.col(strata).alias("stratum"))
    if method == "hash":
        return rows.withColumn("fold", (hashed("subject_id", seed=seed) % n).cast("int"))
    return ranked(rows, "subject_id", ["stratum"], seed).select("subject_id", "stratum", ((F.col("rank") - 1) % n).cast("int").alias("fold"))


def by_visit(visits: DataFrame, n: int = 10, strata: str = "y_return", seed: int = 42) -> DataFrame:
    """(visit_id, stratum, fold): visits taken as independent, so patients cross folds; kept as the flawed comparison."""
    rows = visits.select("visit_id", F.col(strata).alias("stratum"))
    return ranked(rows, "visit_id", ["stratum"], seed).select("visit_id", "stratum", ((F.col("rank") - 1) % n).cast("int").alias("fold"))


def rotation(spark: SparkSession, n: int = 10, n_val: int = 1) -> DataFrame:
    """(iter, fold, role): iteration i tests fold i, validates on the next ``n_val`` and trains on the others."""
    i, f = spark.range(n).select(F.col("id").cast("int").alias("iter")), spark.range(n).select(F.col("id").cast("int").alias("fold"))
    ahead = F.pmod(F.col("fold") - F.col("iter"), F.lit(n))
    return i.crossJoin(F.broadcast(f)).select("iter", "fold", F.when(ahead == 0, "test").when(ahead <= n_val, "validation").otherwise("train").alias("role"))


def balance(rows: DataFrame, label: str = "y_return", key: str = "visit_id", seed: int = 42, iteration: int | Column = 0, by: list[str] | None = None, roles: tuple[str, ...] | None = None, method: str = "exact") -> DataFrame:
    """All positives and, in each group of ``by``, as many negatives in hash order of (key, seed, iteration).

    ``roles``: only rows of these roles are balanced, the rest is kept whole. ``threshold`` takes negatives below a hash
    threshold instead: no ranks, and even on average.
    """
    groups = by or []
    scope = F.col("role").isin(*roles) if roles else F.lit(True)
    wanted = rows.filter(scope).groupBy(*groups).agg(F.sum(label).alias("_p"), F.count("*").alias("_all")) if groups else rows.filter(scope).agg(F.sum(label).alias("_p"), F.count("*").alias("_all"))
    mark = F.concat(F.lit(f"{seed}/"), iteration.cast("string")) if isinstance(iteration, Column) else f"{seed}/{iteration}"
    joined = (lambda d: d.join(F.broadcast(wanted), groups)) if groups else (lambda d: d.join(F.broadcast(wanted)))
    inside = rows.filter(scope)
    positive, negative = inside.filter(F.col(label) == 1), inside.filter(F.col(label) == 0)
    if method == "threshold":
        some = joined(negative).filter(uniform(key, seed=mark) < F.col("_p") / (F.col("_all") - F.col("_p"))).drop("_p", "_all")
    else:
        some = joined(ranked(negative, key, groups or [label], mark)).filter(F.col("rank") <= F.col("_p")).drop("rank", "_p", "_all")
    out = positive.unionByName(some)
    return out.unionByName(rows.filter(~scope)) if roles else out


def balance_once(rows: DataFrame, label: str = "y_return", key: str = "visit_id", seed: int = 42) -> DataFrame:
    """One balanced sample, fixed before any fold is drawn."""
    return balance(rows, label, key, seed, 0)


def expand(folds: DataFrame, visits: DataFrame, seed: int = 42) -> DataFrame:
    """Visits of the folds' patients, in hash order inside each partition: mixed for training without a global sort."""
    return visits.join(folds.select("subject_id", "stratum", "fold"), "subject_id").withColumn("_h", hashed("visit_id", seed=seed)).sortWithinPartitions("_h").drop("_h")


def iterative_label_split(samples: DataFrame, ratios: dict[str, float], seed: int = 42) -> DataFrame:
    """(key, split): multi-label stratification, rarest labels first.

    ``samples``: (key, labels). A sample is dealt by its rarest label. Labels of like frequency (a factor of two) make a round; before
    each round the splits' remaining demand for every label is counted from all that earlier rounds dealt, and the round's samples
    of a label are dealt in hash order by that demand. Rounds grow with the logarithm of the samples. Samples without labels are dealt by the ratios.
    """
    total = sum(ratios.values())
    long = samples.select("key", F.explode("labels").alias("label")).distinct()
    counts = written(long.groupBy("label").agg(F.count("*").alias("n")))
    tier = long.join(counts, "label").groupBy("key").agg(F.min(F.struct("n", "label")).alias("r")).select("key", F.col("r.label").alias("label"), F.floor(F.log2("r.n")).cast("int").alias("round"))
    tier = samples.select("key").distinct().join(tier, "key", "left").select("key", F.col("label").cast("string").alias("label"), F.coalesce("round", F.lit(-1)).alias("round"))
    places = Window.partitionBy("label")
    ranks = ranked(tier.withColumn("_t", F.coalesce("label", F.lit(""))), "key", ["_t"], seed).drop("_t")
    ranks = written(ranks.withColumn("place", (F.col("rank") - 0.5) / F.count("*").over(places)).select("key", "label", "round", "place"))
    dealt = None
    for r in sorted(x["round"] for x in ranks.select("round").distinct().collect()):
        rows = ranks.filter(F.col("round") == r)
        if dealt is not None:
            have = dealt.join(long, "key").groupBy("label").agg(*(F.sum((F.col("split") == s).cast("int")).alias(f"_h_{s}") for s in ratios))
            need = counts.join(have, "label", "left").select(F.col("label").cast("string").alias("label"), *(F.greatest(F.col("n") * (v / total) - F.coalesce(f"_h_{s}", F.lit(0)), F.lit(0.0)).alias(f"_d_{s}") for s, v in ratios.items()))
            rows = rows.join(need, "label", "left")
        else:
            rows = rows.select("*", *(F.lit(float(v)).alias(f"_d_{s}") for s, v in ratios.items()))
        # Without any demand left the ratios hold.
        whole = sum((F.coalesce(f"_d_{s}", F.lit(0.0)) for s in ratios), F.lit(0.0))
        split, upto = F.lit(None).cast("string"), F.lit(0.0)
        for s, v in ratios.items():
            upto = upto + F.when(whole > 0, F.coalesce(f"_d_{s}", F.lit(0.0)) / whole).otherwise(F.lit(v / total))
            split = F.coalesce(split, F.when(F.col("place") < upto, F.lit(s)))
        part = written(rows.select("key", F.coalesce(split, F.lit(list(ratios)[-1])).alias("split")))
        dealt = part if dealt is None else dealt.unionByName(part)
    return dealt if dealt is not None else samples.select("key", F.lit(None).cast("string").alias("split"))


def random_holdout(rows: DataFrame, key: str = "visit_id", runs: int = 3, validation: float = 0.15, seed: int = 42) -> DataFrame:
    """(key, run, split): independent train and validation draws without a test part."""
    each = rows.select(key).withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    return each.withColumn("split", F.when(uniform(F.col(key), F.col("run"), seed=seed) < validation, "validation").otherwise("train"))


def audit_subjects(roles: DataFrame) -> DataFrame:
    """Patients in more than one role of an iteration: (iter, subject_id, roles)."""
    return roles.groupBy("iter", "subject_id").agg(F.countDistinct("role").alias("roles")).filter("roles > 1")


def audit_never_tested(rows: DataFrame, roles: DataFrame, key: str = "visit_id") -> DataFrame:
    """Rows that no iteration tests."""
    return rows.select(key).exceptAll(roles.filter(F.col("role") == "test").select(key).distinct())


def audit_label_input(direction: str, features: list[str]) -> list[str]:
    """Features of which the label is a function: a backward label is one of the prior gap."""
    return [f for f in features if direction == "backward" and f.startswith("gap")]


def audit_encoder(fit_rows: DataFrame, roles: DataFrame, key: str = "visit_id") -> DataFrame:
    """Test rows that a label-tuned encoder was fitted on."""
    return roles.filter(F.col("role") == "test").join(fit_rows.select(key).distinct(), key, "left_semi")


def text_overlap(docs: DataFrame, benchmark: DataFrame, n: int = 8) -> DataFrame:
    """(doc_id, item_id, shared): distinct word n-grams in common, by an equality join on their hashes; no cross product."""

    def shingles(df: DataFrame, key: str) -> DataFrame:
        words = df.select(key, F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "").alias("w")).filter(F.size("w") >= n)
        return words.select(key, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - n + 1), lambda i: F.xxhash64(F.array_join(F.slice("w", i, n), " "))))).alias("g"))

    return shingles(docs, "doc_id").join(shingles(benchmark, "item_id"), "g").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))


def report(rows: DataFrame, label: str = "y_return", how: str = "rollup") -> DataFrame:
    """Visits and patients per fold and label with subtotals; null marks a total."""
    grouped = (rows.rollup if how == "rollup" else rows.cube)("fold", label)
    return grouped.agg(F.count("*").alias("visits"), F.countDistinct("subject_id").alias("patients"))
