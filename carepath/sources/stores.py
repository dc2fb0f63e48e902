"""Where intermediate tables go: the shared folder that the cluster names, or one of our own where none is named."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}


def scratch(spark: SparkSession) -> str:
    """A new folder's path under ``spark.checkpoint.dir``; on one machine without that setting, under a temporary folder."""
    top = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not top:
        app = spark.sparkContext.applicationId
        if app not in _own:
            alone = re.match(r"local(\[|$)", spark.sparkContext.master)
            _own[app] = tempfile.mkdtemp(prefix="carepath-") if alone else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
        top = _own[app]
    return f"{top.rstrip('/')}/carepath/{spark.sparkContext.applicationId}/{uuid.uuid4().hex[:12]}"


def written(df: DataFrame) -> DataFrame:
    """The rows as a Parquet table in the shared folder; lineage ends there."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
