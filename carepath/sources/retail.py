"""Orders as hospital visits: customers are subjects, orders visits, order lines codes, documents notes.

There is no discharge date in these tables. The stand-in: a stay of 1 + (sum of line quantities mod 14) days, one day
for an order without lines.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.sources.tables import load


def encounters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(subject_id, visit_id, admit_ts, discharge_ts, urgency)."""
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity"]).groupBy("l_orderkey").agg(F.sum(F.col("l_quantity").cast("bigint")).alias("q"))
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority"])
    days = F.coalesce(F.pmod("q", F.lit(14)) + 1, F.lit(1)).cast("int")
    joined = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    stay = F.make_dt_interval(days=days)
    return joined.select(F.col("o_custkey").alias("subject_id"), F.col("o_orderkey").alias("visit_id"), F.col("o_orderdate").alias("admit_ts"), (F.col("o_orderdate") + stay).alias("discharge_ts"), F.col("o_orderpriority").alias("urgency"))


def urgent(urgency: Column) -> Column:
    return urgency.isin("1-URGENT", "2-HIGH")


def code_events(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """(visit_id, code, seq, tie): D by line number, P by line number, M (part-supplier pairs) by ship date."""
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate"])
    code = {"D": F.col("l_partkey").cast("string"), "P": F.col("l_suppkey").cast("string"), "M": F.concat_ws("-", "l_partkey", "l_suppkey")}[kind]
    seq = F.unix_date(F.to_date("l_shipdate")) if kind == "M" else F.col("l_linenumber")
    return lines.select(F.col("l_orderkey").alias("visit_id"), code.alias("code"), seq.alias("seq"), F.struct("l_partkey", "l_suppkey").alias("tie"))


def code_dict(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """(code, parent, grp, concept, description). Medications have their part's."""
    if kind == "P":
        s = load(spark, sf_dir, "supplier", ["s_suppkey", "s_name", "s_nationkey"]).join(F.broadcast(load(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
        nation = F.col("s_nationkey").cast("string")
        return s.select(F.col("s_suppkey").cast("string").alias("code"), nation.alias("parent"), nation.alias("grp"), F.col("n_name").alias("concept"), F.concat_ws(" ", "s_name", "n_name").alias("description"))
    p = load(spark, sf_dir, "part", ["p_partkey", "p_name", "p_brand", "p_type"])
    return p.select(F.col("p_partkey").cast("string").alias("code"), F.concat_ws("|", "p_brand", "p_type").alias("parent"), F.col("p_brand").alias("grp"), F.col("p_name").alias("concept"), F.concat_ws(" ", "p_name", "p_type", "p_brand").alias("description"))


def notes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(visit_id, note_id, category, text): a document is the note of the order with its id."""
    return load(spark, sf_dir, "documents", ["doc_id", "source", "text"]).select(F.col("doc_id").alias("visit_id"), F.col("doc_id").alias("note_id"), F.col("source").alias("category"), "text")
