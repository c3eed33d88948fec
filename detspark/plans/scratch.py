"""Shared scratch space: lineage is cut by Parquet files that every executor can read."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """Folder named by ``spark.checkpoint.dir``.

    Where the session names none, a folder in the warehouse, which all executors share; a temporary one only in local mode
    (tests), where driver and executors are one process.
    """
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not named:
        own = tempfile.mkdtemp(prefix="detspark-") if context.master.startswith("local") else f"{spark.conf.get('spark.sql.warehouse.dir')}/detspark-scratch"
        context.setCheckpointDir(own)
        named = context.getCheckpointDir()
    return named.rstrip("/")


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


#: bytes of a row group, which a writing task holds in memory
ROW_GROUP = 32 << 20


def _written(frame: DataFrame, path: str) -> DataFrame:
    frame.write.option("parquet.block.size", ROW_GROUP).parquet(path)
    return frame.sparkSession.read.schema(frame.schema).parquet(path)


def staged(frame: DataFrame, tag: str = "stage") -> DataFrame:
    """Write ``frame`` once and return a scan of the files, so later jobs neither recompute nor hold it in memory."""
    return _written(frame, fresh_path(frame.sparkSession, tag))


def discard(spark: SparkSession, path: str) -> None:
    """Delete a staged folder through the Hadoop file system that owns it."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def children(spark: SparkSession, path: str) -> list[str]:
    """Names in a folder of any file system; none if it is not there."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    system = target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return sorted(s.getPath().getName() for s in system.listStatus(target)) if system.exists(target) else []


def release(spark: SparkSession) -> None:
    """Let the context cleaner drop the shuffle files of finished jobs now, not when the driver next collects garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


class Workspace:
    """Staged tables of one computation, which can be deleted as soon as what was made from them is staged itself."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.paths = spark, {}

    def staged(self, frame: DataFrame, tag: str) -> DataFrame:
        path = fresh_path(self.spark, tag)
        self.paths.setdefault(tag, []).append(path)
        return _written(frame, path)

    def drop(self, *tags: str) -> None:
        for tag in tags:
            for path in self.paths.pop(tag, []):
                discard(self.spark, path)
        release(self.spark)
