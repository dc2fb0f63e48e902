"""A training corpus from ``documents``: toxic texts and near copies go, benchmark passages go, secrets are masked, sources are mixed.

Each stage takes what the one before has kept, as written; all but the last return the columns of ``documents``.
Every decision is by row: rows without an id, and rows of one id with different texts, follow their own text.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.llm import mixing, ngram_join, secrets, tiling, toxicity
from carepath.llm._shared import table, written
from carepath.session import give_back

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def stage(f: Stage) -> Stage:
    """Executors begin with the heap that they need, not with the peak of the stages before."""

    @wraps(f)
    def begun(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        give_back(spark)
        return f(spark, docs, sf_dir)

    return begun


@stage
def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below the cut, by a classifier learned from the labels of these documents."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.scored(docs, model, tuple(docs.columns)).filter(F.col("score") < model.spec.cut).drop("score").toDF(*docs.columns)


@stage
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest id of each group of documents linked by the join (five words, Jaccard 0.8)."""
    return ngram_join.one_of_each(docs)


@stage
def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which no benchmark item is covered."""
    return tiling.without_benchmark(docs, table(spark, sf_dir, "benchmark"))


@stage
def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with each secret replaced by a mask; n_chars follows the new text."""
    masked = secrets.redacted(docs)
    if "n_chars" not in docs.columns:
        return masked
    return masked.withColumn("n_chars", F.when(F.contains("text", F.lit(secrets.MASK)), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))


@stage
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the mix takes, with size, source_size, target, copies and taken beside their own columns."""
    return mixing.mixed(docs, keep=tuple(docs.columns)).filter("copies > 0")


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_jaccard_join", drop_near_copies),
    ("benchmark_decontamination", drop_benchmark),
    ("secret_scan", mask_secrets),
    ("mix_sources", mix_sources),
]

#: Training, links and tilings are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES:
        docs = written(step(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
