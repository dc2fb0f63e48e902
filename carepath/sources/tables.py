"""The given tables with explicit schemas, other formats, and stores that only grow."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from carepath.sources.stores import written

#: Schemas as DDL; reading never infers.
SCHEMAS = {
    "region": "r_regionkey INT, r_name STRING",
    "nation": "n_nationkey INT, n_name STRING, n_regionkey INT",
    "customer": "c_custkey BIGINT, c_name STRING, c_nationkey INT, c_acctbal DOUBLE, c_mktsegment STRING",
    "supplier": "s_suppkey BIGINT, s_name STRING, s_nationkey INT, s_acctbal DOUBLE",
    "part": "p_partkey BIGINT, p_name STRING, p_brand STRING, p_type STRING, p_size INT, p_retailprice DOUBLE",
    "orders": "o_orderkey BIGINT, o_custkey BIGINT, o_orderstatus STRING, o_totalprice DOUBLE, o_orderdate TIMESTAMP_NTZ, o_orderpriority STRING",
    "lineitem": "l_orderkey BIGINT, l_partkey BIGINT, l_suppkey BIGINT, l_linenumber INT, l_quantity DOUBLE, l_extendedprice DOUBLE, l_discount DOUBLE, l_tax DOUBLE, l_returnflag STRING, l_linestatus STRING, l_shipdate TIMESTAMP_NTZ",
    "events": "event_id BIGINT, ts TIMESTAMP_NTZ, user_id BIGINT, event_type STRING, value DOUBLE, props STRING",
    "documents": "doc_id BIGINT, text STRING, lang STRING, source STRING, n_chars BIGINT",
    "labels": "doc_id BIGINT, quality INT, toxic INT",
    "benchmark": "item_id BIGINT, text STRING",
    "pages": "page_id BIGINT, url STRING, html STRING",
    "conversations": "conv_id BIGINT, turn BIGINT, role STRING, text STRING",
    "embeddings": "vec_id BIGINT, embedding ARRAY<FLOAT>, label INT",
}


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    """A table by name; ``cols`` prunes the scan."""
    df = spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def save_as(df: DataFrame, path: str, fmt: str) -> None:
    """Write as parquet, orc, json or csv (with a header)."""
    writer = df.write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def load_as(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    reader = spark.read.schema(schema).format(fmt)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def save_store(df: DataFrame, table: str, bucket_by: str, buckets: int, partition_by: str | None = None) -> None:
    """A store of vectors, bucketed by the key that later joins use, so that they need no exchange on this side."""
    writer = df.write.mode("overwrite").bucketBy(buckets, bucket_by).sortBy(bucket_by)
    (writer.partitionBy(partition_by) if partition_by else writer).saveAsTable(table)


def upsert_missing(df: DataFrame, path: str, key: str) -> DataFrame:
    """Append the rows whose key the Parquet store lacks; returns the rows that were new."""
    spark = df.sparkSession
    hadoop_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    if hadoop_path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop_path):
        new = df.join(spark.read.parquet(path).select(key).distinct(), key, "left_anti")
    else:
        new = df
    new = written(new.dropDuplicates([key]))  # what is new must not be looked up again once it is in the store
    new.write.mode("append").parquet(path)
    return new
