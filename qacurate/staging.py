"""Tables between jobs, in the shared folder of the cluster.

A staged table cuts lineage: a lost executor makes later jobs read the table again instead of
recomputing what led to it. Everything goes under ``spark.checkpoint.dir``; only a local session that
names none (tests, a bench) gets a folder of its own. On a cluster such a folder would not be shared, so
a session without the setting is refused there.
"""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL = "/tmp/checkpoints/qacurate"


def shared_dir(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return (named or _LOCAL).rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; Hadoop removes it when the session's JVM ends."""
    path = f"{shared_dir(spark)}/staged/{name}-{uuid.uuid4().hex}"
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def remove(spark: SparkSession, path: str) -> None:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


@contextmanager
def released_shuffles(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the jobs inside go when each job has ended, instead of at some later collection of garbage.

    For writes of staged tables: what led to a table that is written is not needed again.
    """
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


class Staged:
    """A table written once and read as often as needed."""

    def __init__(self, df: DataFrame, name: str) -> None:
        self.spark = df.sparkSession
        self.path = fresh_path(self.spark, name)
        self.schema = df.schema
        with released_shuffles(self.spark):
            df.write.option("compression", "zstd").parquet(self.path)

    @property
    def df(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        remove(self.spark, self.path)


def stage(df: DataFrame, name: str) -> DataFrame:
    return Staged(df, name).df


def bound_batches(spark: SparkSession, rows: int = 2048) -> None:
    """Limits the rows of an Arrow batch, so that long texts do not fill a Python worker."""
    now = int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000"))
    if now <= 0 or now > rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
    limit = "spark.sql.execution.arrow.maxBytesPerBatch"
    if not 0 < _bytes(spark.conf.get(limit)) <= 8 << 20:
        spark.conf.set(limit, str(8 << 20))


def _bytes(text: str) -> int:
    text = str(text).lower().rstrip("b")
    scale = {"k": 1 << 10, "m": 1 << 20, "g": 1 << 30, "t": 1 << 40}.get(text[-1:], 1)
    return int(text[:-1] if scale > 1 else text) * scale
