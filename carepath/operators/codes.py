"""Ordered code lists, vocabularies and their reduction, padding, multi-hot vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def ordered_list(events: DataFrame, distinct: bool = False, cap: int | None = None) -> DataFrame:
    """(visit_id, codes, n_codes, n_truncated) in order of seq, then tie; ``distinct`` keeps first occurrences.

    A visit's codes meet in one row, so ``cap`` bounds that row where a visit may have very many; what it cuts is counted.
    """
    rows = events.groupBy("visit_id").agg(F.array_sort(F.collect_list(F.struct("seq", "tie", "code"))).alias("_l"))
    codes = F.transform("_l", lambda x: x["code"])
    codes = F.array_distinct(codes) if distinct else codes
    rows = rows.select("visit_id", codes.alias("codes"))
    size = F.size("codes")
    if cap is None:
        return rows.select("visit_id", "codes", size.alias("n_codes"), F.lit(0).alias("n_truncated"))
    return rows.select("visit_id", F.slice("codes", 1, cap).alias("codes"), F.least(size, F.lit(cap)).alias("n_codes"), F.greatest(size - cap, F.lit(0)).alias("n_truncated"))


def map_codes(events: DataFrame, dictionary: DataFrame, to: str, missing: str = "keep", small: bool = False) -> DataFrame:
    """Codes replaced by the dictionary's column ``to``; unmapped ones are kept, dropped or named UNK.

    ``small``: the caller has counted the dictionary, and it is broadcast; else Spark chooses by its size.
    """
    d = dictionary.select(F.col("code").alias("_code"), F.col(to).alias("_to"))
    joined = events.join(F.broadcast(d) if small else d, F.col("code") == F.col("_code"), "inner" if missing == "drop" else "left")
    rest = {"keep": F.col("code"), "UNK": F.lit("UNK"), "drop": F.lit(None).cast("string")}[missing]
    return joined.withColumn("code", F.coalesce("_to", rest)).drop("_code", "_to")


def map_in_row(codes: Column, mapping: dict[str, str]) -> Column:
    """Codes of a list mapped through a small literal map; unmapped ones are dropped."""
    m = F.create_map(*(F.lit(x) for kv in mapping.items() for x in kv))
    return F.filter(F.transform(codes, lambda c: F.element_at(m, c)), lambda c: c.isNotNull())


def condense(code: Column, kind: str) -> Column:
    """A code's parent behind its kind: three characters of a diagnosis (four if it begins with E), two of a procedure."""
    up = F.upper(code)
    if kind == "P":
        return F.concat(F.lit("P_"), F.substring(up, 1, 2))
    return F.concat(F.lit("D_"), F.when(F.startswith(up, F.lit("E")), F.substring(up, 1, 4)).otherwise(F.substring(up, 1, 3)))


PADDING, UNKNOWN, FIRST_ID = 0, 1, 2


def vocabulary(events: DataFrame, order: str = "frequency", min_count: int = 1) -> DataFrame:
    """(code, id, n): ids from 2 on, 0 and 1 being for padding and unknown codes; ordered by frequency or by code."""
    counts = events.groupBy("code").agg(F.count("*").alias("n")).filter(F.col("n") >= min_count)
    w = Window.orderBy(F.desc("n"), "code") if order == "frequency" else Window.orderBy("code")
    return counts.select("code", (F.row_number().over(w) + FIRST_ID - 1).cast("int").alias("id"), "n")


def vocab_report(events: DataFrame, dictionary: DataFrame, approx: bool = False) -> DataFrame:
    """(stage, size): distinct codes raw and after each reduction, in one pass over the joined rows."""
    count = (lambda c: F.approx_count_distinct(c, 0.02)) if approx else F.countDistinct
    d = dictionary.select(F.col("code").alias("_c"), "parent", "grp", "concept")
    one = events.join(d, F.col("code") == F.col("_c"), "left").agg(*(count(c).alias(s) for c, s in (("code", "raw"), ("parent", "parent"), ("grp", "group"), ("concept", "concept"))))
    return one.unpivot([], ["raw", "parent", "group", "concept"], "stage", "size")


def pad(lists: DataFrame, size: int | None = None, side: str = "right", column: str = "codes", fill="") -> DataFrame:
    """``padded`` and ``mask`` of one fixed size: the most distinct codes of any visit unless given."""
    rows = lists.withColumn("_d", F.array_distinct(column))
    if size is None:
        size = rows.agg(F.max(F.size("_d"))).first()[0] or 0
    kept = F.slice("_d", 1, size)
    n = F.size(kept)
    blank, on, off = F.array_repeat(F.lit(fill), F.lit(size) - n), F.array_repeat(F.lit(True), n), F.array_repeat(F.lit(False), F.lit(size) - n)
    order = (lambda a, b: F.concat(a, b)) if side == "right" else (lambda a, b: F.concat(b, a))
    return rows.withColumns({"padded": order(kept, blank), "mask": order(on, off)}).drop("_d")


def ids(lists: DataFrame, vocab: DataFrame, column: str = "codes", key: str = "visit_id") -> DataFrame:
    """Sorted distinct vocabulary ids of each list, sparse; unknown codes have the id 1. Lists without codes give none."""
    long = lists.select(key, F.explode_outer(column).alias("code")).join(vocab.select("code", "id"), "code", "left")
    known = F.when(F.col("code").isNotNull(), F.coalesce("id", F.lit(UNKNOWN)))
    return long.groupBy(key).agg(F.array_sort(F.collect_set(known)).alias("ids"))


def multi_hot(sparse: Column, size: int) -> Column:
    """A dense 0/1 vector of ids FIRST_ID to FIRST_ID + size - 1; for small tests, models densify in their kernels."""
    return F.transform(F.sequence(F.lit(FIRST_ID), F.lit(FIRST_ID + size - 1)), lambda i: F.array_contains(sparse, i).cast("int"))


def describe(dictionary: DataFrame, max_tokens: int = 25) -> DataFrame:
    """(code, text): descriptions cut to the concept encoder's capacity."""
    return dictionary.select("code", F.array_join(F.slice(F.split(F.lower("description"), r"\s+"), 1, max_tokens), " ").alias("text"))
