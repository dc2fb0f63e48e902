"""Notes: category filter, cleaning, chunks of the encoder's capacity, markup."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Titles and degrees that lose their points before symbols are stripped.
ABBREVIATIONS = ("dr.", "mr.", "mrs.", "ms.", "m.d.", "ph.d.", "r.n.", "p.o.", "i.v.")


def select_category(notes: DataFrame, categories: list[str]) -> DataFrame:
    """Notes of some kinds; a filter that reaches the scan."""
    return notes.filter(F.col("category").isin(categories))


def clean(text: Column, abbreviations: tuple[str, ...] = ABBREVIATIONS) -> Column:
    """Lower case, no line breaks, abbreviations without points, no symbols, single spaces."""
    t = F.lower(F.regexp_replace(text, r"[\r\n]+", " "))
    for a in abbreviations:
        t = F.replace(t, F.lit(a), F.lit(a.replace(".", "")))
    return F.trim(F.regexp_replace(F.regexp_replace(t, r"[^\p{L}\p{N} ]", " "), " +", " "))


def chunk(notes: DataFrame, size: int = 512, tail: str = "keep", least: int = 32, unit: str = "word") -> DataFrame:
    """(…, chunk_no, n_chunks, text, n_tokens): runs of ``size`` words, or of words of about ``size`` sub-words with ``unit`` "subword_estimate".

    ``tail``: a last chunk of fewer than ``least`` words is kept, merged into the one before, or dropped; a note's only chunk
    always stays.
    """
    if unit == "subword_estimate":
        return _by_subwords(notes, size)
    words = F.filter(F.split("text", " "), lambda w: w != "")
    rows = notes.withColumn("_w", words).filter(F.size("_w") > 0).withColumn("_n", F.size("_w"))
    full, rest = F.floor(F.col("_n") / size).cast("int"), F.col("_n") % size
    extra = {"keep": (rest > 0).cast("int"), "merge": (rest >= least).cast("int"), "drop": (rest >= least).cast("int")}[tail]
    rows = rows.withColumn("n_chunks", F.greatest(full + extra, F.lit(1)))
    last = F.when((F.col("_i") == F.col("n_chunks") - 1) & F.lit(tail == "merge"), F.col("_n") - F.col("_i") * size).otherwise(F.lit(size))
    each = rows.withColumn("_i", F.explode(F.sequence(F.lit(0), F.col("n_chunks") - 1)))
    part = each.withColumn("_p", F.slice("_w", F.col("_i") * size + 1, last))
    keep = [c for c in notes.columns if c != "text"]
    return part.select(*keep, F.col("_i").alias("chunk_no"), "n_chunks", F.array_join("_p", " ").alias("text"), F.size("_p").alias("n_tokens"))


#: Letters of a sub-word, on average.
SUBWORD = 4


def _by_subwords(notes: DataFrame, size: int) -> DataFrame:
    """A word costs a sub-word for every ``SUBWORD`` letters begun and ends in the chunk where its cost begins; chunks hold the budget but for their last word."""
    keep = [c for c in notes.columns if c != "text"]
    words = notes.select(F.struct(*keep).alias("_k"), F.posexplode(F.filter(F.split("text", " "), lambda w: w != "")).alias("_i", "_w"))
    before = Window.partitionBy("_k").orderBy("_i").rowsBetween(Window.unboundedPreceding, -1)
    cost = F.ceil(F.length("_w") / SUBWORD)
    rows = words.withColumns({"chunk_no": F.floor(F.coalesce(F.sum(cost).over(before), F.lit(0)) / size), "_c": cost})
    # Chunk numbers may skip one where a single word is longer than a chunk.
    made = rows.groupBy("_k", "chunk_no").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("_i", "_w"))), lambda x: x["_w"]), " ").alias("text"), F.sum("_c").cast("int").alias("n_tokens"))
    own = Window.partitionBy("_k")
    made = made.withColumns({"chunk_no": (F.row_number().over(own.orderBy("chunk_no")) - 1).cast("int"), "n_chunks": F.count("*").over(own).cast("int")})
    return made.select("_k.*", "chunk_no", "n_chunks", "text", "n_tokens")


def chunk_stats(chunks: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Notes, chunks and the most chunks of a note."""
    per_note = chunks.groupBy(*(by or []), "note_id").agg(F.count("*").alias("c"))
    return per_note.groupBy(*(by or [])).agg(F.count("*").alias("n_notes"), F.sum("c").alias("n_chunks"), F.max("c").alias("max_chunks"))


def strip_markup(html: Column) -> Column:
    """Text of a page: no comments, scripts, styles or tags."""
    t = F.regexp_replace(html, r"(?s)<!--.*?-->", " ")
    t = F.regexp_replace(t, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(t, r"(?s)<[^>]*>", " "), r"\s+", " "))
