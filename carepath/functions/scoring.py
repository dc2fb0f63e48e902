"""Scores as columns: activations, merging of chunk probabilities, closed-form scorers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def sigmoid(x: Column) -> Column:
    """Without overflow at either end."""
    e = F.exp(-F.abs(x))
    return F.when(x >= 0, 1 / (1 + e)).otherwise(e / (1 + e))


def mish(x: Column) -> Column:
    softplus = F.greatest(x, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x)))
    return x * F.tanh(softplus)


def softmax(scores: DataFrame, logit: str = "z") -> DataFrame:
    """``p`` over the classes of each sample, shifted by its largest logit."""
    w = Window.partitionBy("sample_id")
    e = F.exp(F.col(logit) - F.max(logit).over(w))
    return scores.withColumn("_e", e).withColumn("p", F.col("_e") / F.sum("_e").over(w)).drop("_e")


def layer_norm(x: Column, epsilon: float = 1e-5) -> Column:
    """An array brought to mean 0 and variance 1."""
    n = F.size(x).cast("double")
    mean = F.aggregate(x, F.lit(0.0), lambda a, v: a + v) / n
    square = F.aggregate(x, F.lit(0.0), lambda a, v: a + v * v) / n
    # Both moments are bound once per row, not once per element.
    moments = F.array(F.struct(mean.alias("m"), square.alias("q")))
    return F.element_at(F.transform(moments, lambda s: F.transform(x, lambda v: (v - s["m"]) / F.sqrt(s["q"] - s["m"] * s["m"] + epsilon))), 1)


def linear(x: Column, weights: list[float], bias: float = 0.0) -> Column:
    w = F.array(*(F.lit(float(v)) for v in weights))
    return F.aggregate(F.zip_with(x, w, lambda a, b: a * b), F.lit(float(bias)), lambda a, v: a + v)


def merged(most: Column, mean: Column, k: Column, c: float = 2.0) -> Column:
    """One probability from k chunks: the maximum and the mean, the mean weighing k / c."""
    return (most + mean * k / c) / (1 + k / c)


def merge_chunks(scores: DataFrame, c: float = 2.0, how: str = "blend", per: tuple[str, ...] = ()) -> DataFrame:
    """One score per sample and class (of each ``per``) from those of its chunks: blended, or only the largest or the mean."""
    agg = scores.groupBy(*per, "sample_id", "class_id").agg(F.max("p").alias("_max"), F.avg("p").alias("_mean"), F.count("*").alias("n_chunks"), F.max("y").alias("y"))
    value = {"blend": merged(F.col("_max"), F.col("_mean"), F.col("n_chunks"), c), "max": F.col("_max"), "mean": F.col("_mean")}[how]
    return agg.select(*per, "sample_id", "class_id", "y", "n_chunks", value.alias("p"))


def prevalence_scorer(pairs: DataFrame, train: DataFrame, stay: float = 0.5) -> DataFrame:
    """Closed-form scores of next codes: (1 - stay) * prevalence among the training pairs' next codes, + stay where present now.

    ``pairs``, ``train``: (sample_id, x, y) with sorted class ids. The classes are those of the training labels.
    """
    n = train.agg(F.count("*").alias("n"))
    prior = train.select(F.explode("y").alias("class_id")).groupBy("class_id").agg(F.count("*").alias("c")).crossJoin(F.broadcast(n)).select("class_id", (F.col("c") / F.col("n")).alias("prior"))
    cells = pairs.crossJoin(F.broadcast(prior))
    p = (1 - stay) * F.col("prior") + F.when(F.array_contains("x", F.col("class_id")), F.lit(stay)).otherwise(0.0)
    return cells.select("sample_id", "class_id", F.array_contains("y", F.col("class_id")).cast("int").alias("y"), p.alias("p"))
