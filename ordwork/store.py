"""Intermediate tables of long loops, written to the folder that driver and executors share."""

from __future__ import annotations

import atexit
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

#: Only where the session names no shared folder and runs on one machine, as in tests.
LOCAL_FALLBACK = "/tmp/checkpoints"


def shared_folder(spark: SparkSession) -> str:
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (found or LOCAL_FALLBACK).rstrip("/")


@contextmanager
def tidy(spark: SparkSession):
    """Inside, Spark deletes the shuffle files of each action when it ends, not when its driver next collects garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before) if before is not None else spark.conf.unset(name)


class Store:
    """Parquet tables under one folder. A written table cuts lineage and survives the loss of executors."""

    def __init__(self, spark: SparkSession, name: str, root: str | None = None):
        """Tables go when the process ends, unless root names a folder that is to outlive it."""
        self.spark, self.root, self.n = spark, root or f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}", 0
        self.tag = uuid.uuid4().hex[:8] + "-" if root else ""
        if not root:
            atexit.register(self.delete, self.root)

    def path(self, name: str) -> str:
        self.n += 1
        return f"{self.root}/{self.tag}{self.n:05d}-{name}"

    def write(self, frame: DataFrame, name: str, partition_by: str | None = None) -> str:
        path = self.path(name)
        writer = frame.write.option("compression", "zstd")
        with tidy(self.spark):
            (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
        return path

    def read(self, paths: str | list[str], schema: StructType) -> DataFrame:
        paths = [paths] if isinstance(paths, str) else paths
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def save(self, frame: DataFrame, name: str) -> DataFrame:
        return self.read(self.write(frame, name), frame.schema)

    def exists(self, path: str) -> bool:
        target = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return target.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(target)

    def delete(self, path: str) -> None:
        try:
            target = self.spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # noqa: BLE001  the session may have ended
            pass
