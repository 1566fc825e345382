"""Inputs: tables as Parquet, other formats with a given schema, and a table read as a stream."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def load_table(spark: SparkSession, sf_dir: str, name: str, cols: Sequence[str] = ()) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def load_any(spark: SparkSession, kind: str, path: str, schema: StructType | str, **options: str) -> DataFrame:
    """CSV, JSON or another format; the schema is given, never inferred."""
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def stream_table(spark: SparkSession, folder: str, schema: StructType, time: str = "ts", late: str = "1 hour", files: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream, with a watermark; a time without zone is read in the session's."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)
    return rows.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, late)
