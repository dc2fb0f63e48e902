"""A session for tests and benches, and what a session given from outside needs."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def build(cores: int = 8, memory: str = "8g", partitions: int | None = None) -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(partitions or cores))
        .config("spark.driver.memory", memory)
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .getOrCreate()
    )


def ensure_importable(spark: SparkSession) -> None:
    """Let Python workers find this package where it isn't installed; a cluster's executors have it installed or shipped."""
    root = str(Path(__file__).resolve().parent.parent)
    given = spark.sparkContext.environment.get("PYTHONPATH", os.environ.get("PYTHONPATH", ""))
    if root not in given.split(":"):
        spark.sparkContext.environment["PYTHONPATH"] = f"{root}:{given}" if given else root


#: For Python workers: what they have freed goes back to the system at once, instead of staying with a worker that waits for its next task.
LEAN = {"ARROW_DEFAULT_MEMORY_POOL": "system", "MALLOC_TRIM_THRESHOLD_": str(1 << 20), "MALLOC_MMAP_THRESHOLD_": str(1 << 18), "MALLOC_ARENA_MAX": "2"}


def lean_workers(spark: SparkSession) -> None:
    """Workers started from now on get ``LEAN``; what the session sets itself stays."""
    for name, value in LEAN.items():
        spark.sparkContext.environment.setdefault(name, value)


def give_back(spark: SparkSession) -> None:
    """Executors return the heap that they don't use to the system; it shrinks in a full collection only, and else stays at its peak beside the Python workers."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).collect()
