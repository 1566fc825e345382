"""Sketch functions for SQL: an aggregate over groups, a scalar estimate of a stored sketch, and a table of its tiers."""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import UserDefinedTableFunction

from floorcount.operators.levels import hashed, registers
from floorcount.operators.levels import levels_of as levels_of_rows

HEAD = struct.Struct("<i")


def pack_levels(levels: np.ndarray) -> bytes:
    """m and one signed byte a register, -1 where empty."""
    return HEAD.pack(len(levels)) + levels.astype(np.int8).tobytes()


def unpack_levels(sketch: bytes) -> np.ndarray:
    m = HEAD.unpack_from(sketch)[0]
    return np.frombuffer(sketch, dtype=np.int8, count=m, offset=HEAD.size).astype(np.int64)


def tier_rows(sketch: bytes) -> Iterator[tuple[int, int, float]]:
    """(tier, registers below, linear count) for tiers that can be counted at."""
    lvl = unpack_levels(sketch)
    m = len(lvl)
    for t in range(64):
        z = int(np.count_nonzero(lvl < t))
        if 0 < z < m:
            yield t, z, 2.0**t * m * math.log(m / z)


def tlc(sketch: bytes, p: float = 4.5) -> float:
    w = e = 0.0
    m = HEAD.unpack_from(sketch)[0]
    for t, z, value in tier_rows(sketch):
        weight = (math.sqrt(2 / math.pi) * math.sqrt((m - z) / (m * z)) / math.log(m / z)) ** -p
        w, e = w + weight, e + weight * math.log(value)
    return math.exp(e / w) if w else 0.0


def sketch_agg(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str], m: int = 2048, kind: str = "xxhash64", width: int = 64) -> DataFrame:
    """Rows (by..., sketch): registers are aggregated as rows, and the at most m of a group are packed into one value."""
    rows = levels_of_rows(hashed(df, cols, by, kind), by, m, width)
    held = registers(rows, by).groupBy(*by).agg(F.collect_list((F.col("reg") * 64 + F.col("lvl")).cast("int")).alias("codes"))

    @F.pandas_udf(T.BinaryType())
    def packed(codes: pd.Series) -> pd.Series:
        def one(c: np.ndarray) -> bytes:
            out = np.full(m, -1, dtype=np.int64)
            out[np.asarray(c) // 64] = np.asarray(c) % 64
            return pack_levels(out)

        return codes.map(one)

    return held.select(*by, packed("codes").alias("sketch"))


def merge_agg(sketches: DataFrame, by: Sequence[str] = (), sketch: str = "sketch") -> DataFrame:
    """Rows (by..., sketch): stored sketches of one size joined by the larger register, each register a row on the way."""

    @F.pandas_udf("array<int>")
    def one(s: pd.Series) -> pd.Series:
        return s.map(lambda x: [] if x is None else unpack_levels(bytes(x)).astype(np.int32))

    each = sketches.select(*by, F.posexplode(one(F.col(sketch))).alias("reg", "lvl"))
    best = each.groupBy(*by, "reg").agg(F.max("lvl").alias("lvl")).groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("reg", "lvl"))).alias("regs"))

    @F.pandas_udf(T.BinaryType())
    def packed(levels: pd.Series) -> pd.Series:
        return levels.map(lambda c: pack_levels(np.asarray(c, dtype=np.int64)))

    return best.select(*by, packed(F.transform("regs", lambda x: x["lvl"])).alias("sketch"))


def linear(sketch: bytes) -> float:
    """Linear counting at the floor."""
    lvl = unpack_levels(sketch)
    t = max(int(lvl.min()) + 1, 0)
    return 2.0**t * len(lvl) * math.log(len(lvl) / max(int(np.count_nonzero(lvl < t)), 0.5))


def classic(sketch: bytes) -> float:
    lvl = unpack_levels(sketch)
    m, empty = len(lvl), int(np.count_nonzero(lvl < 0))
    raw = 0.7213 / (1 + 1.079 / m) * 2 * m * m / (float(np.sum(2.0 ** -lvl[lvl >= 0].astype(float))) + 2.0 * empty)
    return m * math.log(m / empty) if empty and raw <= 2.5 * m else raw


METHODS = {"tlc": tlc, "lc_floor": linear, "hll": classic}


@F.pandas_udf(T.DoubleType())
def sketch_estimate(sketch: pd.Series) -> pd.Series:
    return sketch.map(lambda s: None if s is None else tlc(bytes(s)))


@F.pandas_udf(T.DoubleType())
def sketch_estimate_by(sketch: pd.Series, method: pd.Series) -> pd.Series:
    """The estimate of a stored sketch by one of METHODS."""
    return pd.Series([None if s is None else METHODS[k](bytes(s)) for s, k in zip(sketch, method)], dtype=float)


@F.pandas_udf(T.BinaryType())
def sketch_merge(a: pd.Series, b: pd.Series) -> pd.Series:
    """Two stored sketches of one size as one; a null one is left out."""

    def both(x, y):
        if x is None or y is None:
            return x if y is None else y
        return pack_levels(np.maximum(unpack_levels(bytes(x)), unpack_levels(bytes(y))))

    return pd.Series([both(x, y) for x, y in zip(a, b)])


class _Tiers:
    def eval(self, sketch: bytes):
        if sketch is not None:
            yield from tier_rows(bytes(sketch))


def tiers_udtf() -> UserDefinedTableFunction:
    return F.udtf(_Tiers, returnType="tier int, z int, estimate double")


def register(spark: SparkSession) -> None:
    """sketch_estimate(sketch), sketch_estimate_by(sketch, method), sketch_merge(a, b) and sketch_tiers(sketch) for SQL."""
    spark.udf.register("sketch_estimate_by", sketch_estimate_by)
    spark.udf.register("sketch_estimate", sketch_estimate)
    spark.udf.register("sketch_merge", sketch_merge)
    spark.udtf.register("sketch_tiers", tiers_udtf())
