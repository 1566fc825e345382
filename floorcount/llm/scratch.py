"""Tables written between steps, in the shared folder the cluster names."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import wraps

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a folder of this machine only where all tasks run on it too (local master)."""
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="floorcount-")
        context.setCheckpointDir(named)
    return named.rstrip("/")


class Scratch:
    """Parquet tables of one operator call; they survive lost executors and cut the lineage.

    The tables stay readable until release(), which the caller runs once nothing reads the result any more.
    """

    def __init__(self, spark: SparkSession, label: str = "step"):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/floorcount/{label}-{uuid.uuid4().hex}"

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def keep(self, df: DataFrame, name: str, partition_by: str | None = None) -> DataFrame:
        """Writes df and returns the written table."""
        writer = df.write.mode("overwrite")
        (writer.partitionBy(partition_by) if partition_by else writer).parquet(self.path(name))
        schema = df.schema
        return self.spark.read.schema(schema).parquet(self.path(name))

    def drop(self, name: str = "") -> None:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path(name) if name else self.root)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    def release(self) -> None:
        self.drop()


class Bucketed:
    """A table dealt by one column once, which joins on that column then read without an exchange."""

    def __init__(self, scratch: Scratch, name: str, column: str):
        self.scratch, self.column, self.name = scratch, column, f"floorcount_{name}_{scratch.root.rsplit('-', 1)[-1]}"

    def keep(self, df: DataFrame) -> DataFrame:
        """Writes df in as many parts as joins have, and returns the written table."""
        parts = int(self.scratch.spark.conf.get("spark.sql.shuffle.partitions"))
        df.write.bucketBy(parts, self.column).option("path", self.scratch.path(self.name)).saveAsTable(self.name)
        return self.scratch.spark.table(self.name)

    def drop(self) -> None:
        """Takes the table out of the catalog; its files go with the scratch."""
        self.scratch.spark.sql(f"DROP TABLE IF EXISTS {self.name}")


def must_be_free(df: DataFrame, *names: str) -> None:
    """Raises if df has a column of one of the names, in any case."""
    taken = {c.lower() for c in df.columns}
    for name in names:
        if name.lower() in taken:
            raise ValueError(f"there is a column {name} already")


def free_name(df: DataFrame, wanted: str) -> str:
    """wanted, or wanted with underscores where df has such a column already."""
    taken = {c.lower() for c in df.columns}
    while wanted.lower() in taken:
        wanted = f"_{wanted}"
    return wanted


def give_back() -> None:
    """Returns freed memory to the system: a worker process that waits for its next task should hold little."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library can
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """run(), with its memory given back at the end of each task."""

    @wraps(run)
    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return task
