"""The registered queries of this subpackage, each over its whole table, and their DuckDB twins where SQL has one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.llm import chaining, mixing, ngram_join, quality, secrets, suffixes, tiling, tokens, toxicity, warc
from carepath.llm._shared import scratch_path, table

Query = Callable[[SparkSession, str], DataFrame]


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans")


def op2_warc_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = scratch_path(spark, "warc")
    warc.write(table(spark, sf_dir, "pages"), folder)
    return warc.read(spark, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_fuzzy_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chaining.repeated_passages(table(spark, sf_dir, "documents"))


def op4_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.deduplicated(table(spark, sf_dir, "documents"))


def op5_rule_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    book = quality.apply_policy(quality.ledger(table(spark, sf_dir, "documents")), "3")
    base_failed = quality.fails(quality.POLICIES["base"])
    return book.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base_failed.alias("base_failed"), (F.col("kept") & ~base_failed).alias("kept"), "failures")


def op6_toxicity_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    cut = toxicity.threshold_for(F.col("lang"), model)
    return toxicity.scored(docs, model, ("doc_id", "lang")).select(
        "doc_id", (toxicity.remainder(F.col("doc_id")) == 2).alias("held_out"), "score",
        (F.col("score") >= 0.3).cast("int").alias("predicted"), (F.col("score") >= cut).cast("int").alias("predicted_by_lang"),
    )


def op7_pareto_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix = mixing.mixed(table(spark, sf_dir, "documents"))
    return mix.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), "taken")


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = ngram_join.JoinSpec(shingle=3, percent=90)
    return ngram_join.joined(table(spark, sf_dir, "documents"), spec).select("doc_id", "n_shingles", "component_id")


def op9_fst_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    found = tokens.counted(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
    return found.withColumn("over_limit", F.col("n_tokens") > 2048)


def op10_greedy_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tiling.tiled(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in (op1_secret_scan, op2_warc_shards, op3_fuzzy_passages, op4_suffix_repeats, op5_rule_ledger, op6_toxicity_cnn, op7_pareto_mix, op8_jaccard_join, op9_fst_token_counts, op10_greedy_tiling, pipeline)}


def oracle_sql() -> dict[str, str]:
    from carepath.llm.oracles import ORACLES

    return dict(ORACLES)
