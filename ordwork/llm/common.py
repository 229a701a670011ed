"""What the operators of this subpackage share: reading, stored intermediate tables, Arrow plumbing."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

#: Only used where the session names no shared folder (tests in local mode).
LOCAL_FALLBACK = "/tmp/checkpoints"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a local one where it is unset and all is one machine."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (found or LOCAL_FALLBACK).rstrip("/")


class Scratch:
    """Intermediate tables as Parquet in the shared folder, so that a lost executor costs no recomputation.

    ``save`` writes a frame and returns it reread, which also cuts its lineage. ``drop`` deletes one table
    early. What is left goes when the Python process ends, as lazily evaluated results may still read it.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root = spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        self.count = 0
        atexit.register(self.delete, self.root)

    def save(self, frame: DataFrame, name: str = "t", partition_by: str | None = None) -> DataFrame:
        self.count += 1
        path = f"{self.root}/{self.count:03d}-{name}"
        writer = frame.write.option("compression", "zstd")
        with tidy(self.spark):
            (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
        out = self.spark.read.schema(frame.schema).parquet(path)
        out.scratch_path = path
        return out

    def drop(self, frame: DataFrame) -> None:
        self.delete(frame.scratch_path)

    def delete(self, path: str) -> None:
        try:
            jvm = self.spark._jvm
            target = jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # noqa: BLE001  the session may have ended before the process
            pass


#: Rows that go to Python at a time: texts may be long, and both sides hold a batch.
BATCH_ROWS = "1000"


@contextmanager
def tidy(spark: SparkSession):
    """Inside, Spark deletes the shuffle files of each action when it ends, not when its driver next collects garbage, and
    hands smaller batches to Python. Both are settings of the running session and are put back."""
    wanted = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": BATCH_ROWS}
    before = {name: spark.conf.get(name, None) for name in wanted}
    for name, value in wanted.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.set(name, value) if value is not None else spark.conf.unset(name)


def without(frame: DataFrame, *names: str) -> DataFrame:
    """frame without columns of these names, whatever their case."""
    low = {n.lower() for n in names}
    return frame.select(*[F.col(f"`{c}`") for c in frame.columns if c.lower() not in low])


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(all UTF-8 bytes of a string column as one uint8 array, offsets of n+1 rows); null counts as empty."""
    column = column.fill_null("") if column.null_count else column
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    width = np.int64 if pa.types.is_large_string(column.type) else np.int32
    offsets = np.frombuffer(column.buffers()[1], width)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def portions(offsets: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``most`` bytes, or one row where a row alone is longer."""
    at, n = 0, len(offsets) - 1
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1
        end = min(max(end, at + 1), n)
        yield at, end
        at = end


_KEPT: dict[str, object] = {}


def kept_by_worker(token: str, make: Callable[[], object]):
    """What make gives, kept by a Python worker from task to task until another token is asked for."""
    if token not in _KEPT:
        _KEPT.clear()
        _KEPT[token] = make()
    return _KEPT[token]


def as_array(column, kind: pa.DataType) -> pa.Array:
    if isinstance(column, pa.Array):
        return column if column.type == kind else column.cast(kind)
    return pa.array(column, kind)


def map_batches(frame: DataFrame, each: Callable[[pa.RecordBatch], Iterator[dict]], schema: str | StructType) -> DataFrame:
    """mapInArrow of a function that yields dicts of columns for every input batch."""
    schema = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                for columns in each(batch):
                    yield pa.RecordBatch.from_arrays([as_array(columns[f.name], f.type) for f in arrow], schema=arrow)

    return frame.mapInArrow(run, schema)


def let(value, body: Callable):
    """body applied to value, evaluated once a row (a column that is merely named may be inlined at each use)."""
    return F.transform(F.array(value), body)[0]


def ascii_lower(column):
    """A-Z lower-cased, everything else as it is."""
    return F.translate(column, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
