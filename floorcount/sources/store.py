"""Sketches at rest: Parquet, one folder for each kind, packed."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from floorcount.operators.encode import pack, to_floor


def packed_sketches(levels: DataFrame, by: Sequence[str], m: int, spec: str = "floor4") -> DataFrame:
    """Rows (by..., spec, m, floor, words) of four-bit registers."""
    return pack(to_floor(levels, by, m, 4), by, m, 4, 8).select(*by, F.lit(spec).alias("spec"), F.lit(m).alias("m"), "floor", "words")


def save_sketches(df: DataFrame, path: str, mode: str = "append") -> None:
    df.write.mode(mode).partitionBy("spec").parquet(path)


def load_sketches(spark: SparkSession, path: str, spec: str | None = None) -> DataFrame:
    """All sketches, or those of one kind, whose folder alone is then read."""
    df = spark.read.parquet(path)
    return df if spec is None else df.filter(F.col("spec") == spec)
