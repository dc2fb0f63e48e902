"""What the corpus operators share: the shared folder, written intermediate tables, null-safe texts."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from carepath.session import lean_workers

#: Java pattern of the white space that separates words everywhere in this subpackage.
SPACE = r"[\x20\x09-\x0D]+"
#: The same characters, for translate().
SPACE_CHARS = " \t\n\x0b\x0c\r"

_own: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or one of our own where that is unset."""
    if found := spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _own:
        on_one_machine = re.match(r"local(\[|$)", spark.sparkContext.master)
        _own[app] = tempfile.mkdtemp(prefix="carepath-") if on_one_machine else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_scratch"
    return _own[app]


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/carepath/{spark.sparkContext.applicationId}/{tag}-{uuid.uuid4().hex[:12]}"


#: Settings while a table is written. Shuffle files go as soon as the query ends, as what it made is in the table; rows reach Python
#: workers in smaller batches, which take memory outside the heap on either side.
WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": "2500"}


@contextmanager
def _settings(spark: SparkSession, values: dict[str, str]) -> Iterator[None]:
    """Runtime settings for the queries inside; afterwards they are as before."""
    before = {k: spark.conf.get(k, None) for k in values}
    try:
        for k, v in values.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def written(df: DataFrame, tag: str) -> DataFrame:
    """The rows of ``df`` as a Parquet table in the shared folder: lineage ends there and a lost executor costs only a reread."""
    spark = df.sparkSession
    lean_workers(spark)
    path = scratch_path(spark, tag)
    with _settings(spark, WRITING):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of a few numbers that are broadcast at most.
BROADCAST_ROWS = 1_000_000


def if_small(df: DataFrame, most: int = BROADCAST_ROWS, weight: Column | None = None) -> DataFrame:
    """``df`` marked for broadcast if it has ``most`` rows at most, or that sum of ``weight``; it is counted first. Else as it is, to be joined."""
    n = df.limit(most + 1).count() if weight is None else df.agg(F.sum(weight)).first()[0] or 0
    return F.broadcast(df) if n <= most else df


def release(spark: SparkSession) -> None:
    """Delete this application's intermediate tables; frames that still read them must be done."""
    root = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/carepath/{spark.sparkContext.applicationId}")
    root.getFileSystem(spark._jsc.hadoopConfiguration()).delete(root, True)


def text_of(column: str = "text") -> Column:
    """The text, a null one as the empty string."""
    return F.coalesce(F.col(column), F.lit(""))


def words_of(text: Column) -> Column:
    """Words of a text, as an array; no empty strings."""
    return F.array_remove(F.split(text, SPACE), "")


def carried(docs: DataFrame, keep: tuple[str, ...], **more: Column) -> DataFrame:
    """``keep`` as one struct beside further columns, so that no name of theirs can clash with one of an operator's."""
    return docs.select(F.struct(*(F.col(f"`{c}`") for c in keep)).alias("_k"), *(c.alias(n) for n, c in more.items()))


def restored(df: DataFrame, keep: tuple[str, ...], outputs: list[str]) -> DataFrame:
    """The carried columns again, then ``outputs``; a carried one that has an output's name gets the suffix _in."""
    taken = {c.lower() for c in outputs}
    return df.select(*(F.col(f"_k.`{c}`").alias(f"{c}_in" if c.lower() in taken else c) for c in keep), *outputs)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    lean_workers(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
