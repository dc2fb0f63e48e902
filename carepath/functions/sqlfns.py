"""Functions for SQL users: expressions that Catalyst sees through, Arrow UDFs and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from carepath.sources.tables import SCHEMAS, load


def register(spark: SparkSession) -> None:
    """condense_dx, condense_proc, merge_chunks_p as SQL expressions; chunk_text and slide as table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION condense_dx(c STRING) RETURNS STRING RETURN concat('D_', CASE WHEN startswith(upper(c), 'E') THEN substring(upper(c), 1, 4) ELSE substring(upper(c), 1, 3) END)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION condense_proc(c STRING) RETURNS STRING RETURN concat('P_', substring(upper(c), 1, 2))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION merge_chunks_p(m DOUBLE, a DOUBLE, k BIGINT) RETURNS DOUBLE RETURN (m + a * k / 2.0D) / (1 + k / 2.0D)")
    spark.udtf.register("chunk_text", ChunkText)
    spark.udtf.register("slide", Slide)


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in SCHEMAS:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


@udtf(returnType=T.StructType([T.StructField("chunk_no", T.IntegerType()), T.StructField("text", T.StringType()), T.StructField("n_tokens", T.IntegerType())]))
class ChunkText:
    """Chunks of a text, of ``size`` words."""

    def eval(self, text: str, size: int):
        words = [w for w in (text or "").split(" ") if w]
        for n, i in enumerate(range(0, len(words), size)):
            part = words[i : i + size]
            yield n, " ".join(part), len(part)


@udtf(returnType=T.StructType([T.StructField("start", T.IntegerType()), T.StructField("items", T.ArrayType(T.StringType()))]))
class Slide:
    """Windows of k items of an array; one of all items if there are fewer."""

    def eval(self, items: list, k: int):
        items = list(items or [])
        for i in range(max(1, len(items) - k + 1) if items else 0):
            yield i, items[i : i + k]


def logistic_udf(weights: list[float], bias: float):
    """An Arrow UDF that scores array vectors."""
    import numpy as np

    w = np.array(weights)

    @pandas_udf(T.DoubleType())
    def score(x: pd.Series) -> pd.Series:
        z = np.stack(x.to_numpy()) @ w + bias if len(x) else np.zeros(0)
        return pd.Series(1 / (1 + np.exp(-z)))

    return score


@pandas_udf(T.DoubleType())
def aupr_udf(p: pd.Series, y: pd.Series) -> float:
    """Area under precision and recall of one group, as steps; a cross-check of the distributed measure."""
    d = pd.DataFrame({"p": p, "y": y}).groupby("p").agg(pos=("y", "sum"), n=("y", "size")).sort_index(ascending=False)
    tp, n = d["pos"].cumsum(), d["n"].cumsum()
    total = d["pos"].sum()
    return float((tp / n * d["pos"]).sum() / total) if total else float("nan")


def exploded_chunks(notes, size: int = 512):
    """(note_id, chunk_no, text, n_tokens): the table function over a frame of notes, by a lateral join; no name is registered."""
    rows = notes.select("note_id", F.col("text").alias("_note"))
    return rows.lateralJoin(ChunkText(F.col("_note").outer(), F.lit(size))).drop("_note")


def dead_letters(df, column: str):
    """Rows whose JSON in ``column`` can't be parsed."""
    return df.filter(F.col(column).isNotNull() & F.try_parse_json(column).isNull())
