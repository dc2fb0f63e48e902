"""Rule bitmask ledger: each document's rules are evaluated once, their failures kept as bits beside the measurements.

A policy is a named, versioned mask over those bits, so that changing a policy or leaving one rule out never reads a
text again. Only DataFrame functions are used: the ledger is one projection over the scan, without any shuffle.

Defined cases: a null or empty text has no words and fails ``few_words``; rules that divide by a count hold (pass)
where the count is 0; repeated rows each get their own ledger row; an empty table gives an empty ledger; further
columns are ignored unless named in ``keep``.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from carepath.llm._shared import SPACE_CHARS, carried, restored, text_of, words_of

#: Fixed values of the rules, in words and per cent.
WINDOW = 8
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """A rule fails where ``fails`` is true of the measurements."""

    name: str
    bit: int
    fails: str


#: Bits are never reused: a withdrawn rule keeps its number.
RULES = (
    Rule("few_words", 0, "n_words < 20"),
    Rule("repeated_windows", 1, "100 * n_repeat_words > 30 * n_words"),
    Rule("repeated_lines", 2, "n_dup_lines >= 3 AND 100 * n_dup_lines > 60 * n_lines"),
    Rule("symbol_heavy", 3, "100 * n_symbols > 25 * word_chars"),
    Rule("word_length", 4, "n_words > 0 AND (word_chars < 2 * n_words - n_words DIV 2 OR word_chars > 20 * n_words)"),
)

BASE = ("few_words", "repeated_windows")


@dataclass(frozen=True)
class Policy:
    """A version of the decision: documents that fail any of ``rules`` go."""

    version: str
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        bits = {r.name: r.bit for r in RULES}
        return reduce(lambda m, name: m | 1 << bits[name], self.rules, 0)


POLICIES = {p.version: p for p in (Policy("base", BASE), Policy("2", (*BASE, "repeated_lines")), Policy("3", tuple(r.name for r in RULES)))}


def measured(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``keep`` and the measurements: n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words."""
    plain = carried(docs, keep, _t=text_of(text))
    lines = F.filter(F.split("_t", "\n"), lambda x: F.length(F.translate(x, SPACE_CHARS, "")) > 0)
    split = plain.select(
        "_k",
        words_of(F.col("_t")).alias("_w"),
        F.length(F.translate("_t", SPACE_CHARS, "")).cast("long").alias("word_chars"),
        (F.length("_t") - F.length(F.translate("_t", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines.alias("_l"),
    )
    counted = split.select(
        "_k", "word_chars", "n_symbols",
        F.size("_w").cast("long").alias("n_words"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.transform("_w", lambda x: F.xxhash64(x)).alias("_h"),
    )
    starts = F.when(F.col("n_words") >= WINDOW, F.sequence(F.lit(1), (F.col("n_words") - (WINDOW - 1)).cast("int"))).otherwise(F.array().cast("array<int>"))
    windows = counted.withColumn("_g", F.transform(starts, lambda i: F.xxhash64(F.slice("_h", i, WINDOW)))).drop("_h")
    # Only texts with some window twice pay for the sort that finds where they are.
    twice = windows.withColumn("_g", F.when(F.size(F.array_distinct("_g")) < F.size("_g"), F.col("_g")))
    ordered = twice.withColumn("_g", F.sort_array(F.transform("_g", lambda x, i: F.struct(x.alias("h"), i.alias("i")))))
    near = lambda x, j: F.coalesce(F.get("_g", j)["h"] == x["h"], F.lit(False))
    at = ordered.withColumn("_g", F.sort_array(F.transform(F.filter("_g", lambda x, i: near(x, i + 1) | near(x, i - 1)), lambda x: x["i"])))
    fresh = F.transform("_g", lambda p, i: F.least(F.lit(WINDOW), F.coalesce(F.get("_g", i + 1), p + WINDOW) - p))
    done = at.withColumn("n_repeat_words", F.coalesce(F.aggregate(fresh, F.lit(0), lambda a, x: a + x), F.lit(0)).cast("long"))
    return restored(done, keep, ["word_chars", "n_symbols", "n_words", "n_lines", "n_dup_lines", "n_repeat_words"])


def ledger(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """Measurements and ``failures``, a long with a bit for each rule that a document fails."""
    bits = (F.when(F.expr(r.fails), F.lit(1 << r.bit)).otherwise(F.lit(0)).cast("long") for r in RULES)
    return measured(docs, keep, text).withColumn("failures", reduce(lambda a, b: a.bitwiseOR(b), bits))


def fails(policy: Policy) -> Column:
    return F.col("failures").bitwiseAND(F.lit(policy.mask).cast("long")) != 0


def apply_policy(book: DataFrame, version: str) -> DataFrame:
    """The ledger with ``kept`` and ``policy``; no text is read again."""
    return book.withColumns({"kept": ~fails(POLICIES[version]), "policy": F.lit(version)})


def patterns(book: DataFrame) -> DataFrame:
    """Documents and words by failure pattern: at most two to the number of rules rows, enough for every policy's totals."""
    return book.groupBy("failures").agg(F.count("*").alias("docs"), F.sum("n_words").alias("words"))


def ablation(book: DataFrame, version: str) -> DataFrame:
    """For each rule of a policy: documents failing it, documents only it rejects, and words won back without it."""
    mask = POLICIES[version].mask
    found = F.col("failures").bitwiseAND(F.lit(mask).cast("long"))
    rules = F.explode(F.array(*(F.struct(F.lit(r.name).alias("rule"), F.lit(1 << r.bit).cast("long").alias("bit")) for r in RULES if mask >> r.bit & 1)))
    each = patterns(book).select("docs", "words", found.alias("found"), rules.alias("r"))
    alone = F.col("found") == F.col("r.bit")
    return each.groupBy(F.col("r.rule").alias("rule")).agg(
        F.sum(F.when(F.col("found").bitwiseAND(F.col("r.bit")) != 0, F.col("docs")).otherwise(0)).alias("failing"),
        F.sum(F.when(alone, F.col("docs")).otherwise(0)).alias("only_this"),
        F.sum(F.when(alone, F.col("words")).otherwise(0)).alias("words_back"),
    )


def overlaps(book: DataFrame) -> DataFrame:
    """Documents that fail both of two rules, for each pair, from the patterns alone."""
    pairs = F.explode(F.array(*(F.struct(F.lit(a.name).alias("a"), F.lit(b.name).alias("b"), F.lit(1 << a.bit | 1 << b.bit).cast("long").alias("both")) for a in RULES for b in RULES if a.bit < b.bit)))
    each = patterns(book).select("failures", "docs", pairs.alias("p"))
    return each.groupBy("p.a", "p.b").agg(F.sum(F.when(F.col("failures").bitwiseAND(F.col("p.both")) == F.col("p.both"), F.col("docs")).otherwise(0)).alias("docs"))
