"""MLlib models as sanity checks of the numpy kernels."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _assembled(rows: DataFrame, features: list[str], label: str) -> DataFrame:
    return VectorAssembler(inputCols=features, outputCol="features").transform(rows.withColumn("label", F.col(label).cast("double")))


def _scores(fitted, rows: DataFrame, key: str) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    out = fitted.transform(rows)
    return out.select(F.col(key).alias("sample_id"), F.lit(0).alias("class_id"), F.col("label").cast("int").alias("y"), vector_to_array("probability")[1].alias("p"))


def logistic(train: DataFrame, test: DataFrame, features: list[str], label: str, key: str = "visit_id") -> DataFrame:
    """Scores of ``test`` by a logistic regression on numeric columns; one call per class makes it one against the rest."""
    return _scores(LogisticRegression(maxIter=50).fit(_assembled(train, features, label)), _assembled(test, features, label), key)


def perceptron(train: DataFrame, test: DataFrame, features: list[str], label: str, hidden: int = 8, key: str = "visit_id") -> DataFrame:
    model = MultilayerPerceptronClassifier(layers=[len(features), hidden, 2], maxIter=100, seed=3)
    return _scores(model.fit(_assembled(train, features, label)), _assembled(test, features, label), key)
