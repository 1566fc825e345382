"""Accuracy over runs and checkpoints, and what sketches cost."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from floorcount.functions.estimators import ESTIMATORS

#: Bits of a register, registers in a word, and bits of a word; words None: packed without loss.
SPECS = {
    "abs6": (6, None, None), "floor3": (3, None, None), "floor4": (4, 8, 32), "floor5": (5, None, None), "hist8": (8, 4, 32), "fhist5": (5, 6, 32), "fhist6": (6, 5, 32),
    "fhist7": (7, 9, 64), "twobit": (2, 16, 32), "offset4_map": (4, 8, 32), "offset3_map": (3, None, None), "offset4_trunc": (4, 8, 32),
}
#: Floor, exit bound, floor count, small bitmap and the like.
FIXED_BYTES = 28


def packed_bytes(spec: str, m: int) -> int:
    bits, per, word = SPECS[spec]
    return -(-m * bits // 8) if per is None else -(-m // per) * word // 8


def packing_efficiency(spec: str) -> float:
    bits, per, word = SPECS[spec]
    return 1.0 if per is None else bits * per / word


def memory_table(spark: SparkSession, sizes: Sequence[int] = (1024, 2048, 2560, 3072, 3584, 4096)) -> DataFrame:
    """Rows (spec, m, bits, bytes, with_state, relative, efficiency) of every spec and size; relative to six bits a register."""
    specs = spark.createDataFrame([(k, v[0], v[1] or 0, v[2] or 0) for k, v in sorted(SPECS.items())], "spec string, bits int, per int, word int")
    grid = specs.crossJoin(spark.createDataFrame([(m,) for m in sizes], "m int"))  # a few dozen rows
    size = F.when(F.col("per") == 0, F.ceil(F.col("m") * F.col("bits") / 8)).otherwise(F.ceil(F.col("m") / F.greatest("per", F.lit(1))) * F.col("word") / 8).cast("long")
    return grid.select("spec", "m", "bits", size.alias("bytes"), (size + FIXED_BYTES).alias("with_state"), F.round(size / (F.col("m") * 6 / 8), 4).alias("relative"), F.round(F.when(F.col("per") == 0, 1.0).otherwise(F.col("bits") * F.col("per") / F.greatest("word", F.lit(1))), 4).alias("efficiency"))


def size_law(spec: str, m: int, largest: float) -> float:
    """Bits that are needed to count up to `largest`: a fixed width and a shared floor, or registers that must hold every level."""
    bits = SPECS[spec][0]
    deepest = math.log2(max(largest / m, 1)) + math.log2(m) + 2
    return bits * m + math.ceil(math.log2(deepest + 1)) if spec.startswith(("floor", "fhist", "offset")) else m * max(bits, math.ceil(math.log2(deepest + 1)))


def with_errors(df: DataFrame, truth: str, estimate: str) -> DataFrame:
    signed = (F.col(estimate) - F.col(truth)) / F.col(truth)
    return df.withColumns({"signed": signed, "absolute": F.abs(signed), "squared": signed * signed})


def by_checkpoint(errors: DataFrame, keys: Sequence[str] = (), checkpoint: str = "checkpoint") -> DataFrame:
    """Rows (keys..., checkpoint, runs, mae, bias, deviation)."""
    return errors.groupBy(*keys, checkpoint).agg(F.count(F.lit(1)).alias("runs"), F.avg("absolute").alias("mae"), F.avg("signed").alias("bias"), F.stddev_pop("signed").alias("deviation"))


def weighted(curve: DataFrame, keys: Sequence[str] = (), checkpoint: str = "checkpoint") -> DataFrame:
    """Rows (keys..., peak, by_log, by_size, by_width): the largest error, and its means over checkpoints with three weights."""
    width = F.col(checkpoint) - F.coalesce(F.lag(checkpoint).over(W.partitionBy(*keys).orderBy(checkpoint)), F.lit(0))
    c = F.col(checkpoint)
    w = curve.withColumn("width", width)
    agg = [F.max("mae").alias("peak"), F.avg("mae").alias("by_log"), (F.sum(F.col("mae") * c) / F.sum(c)).alias("by_size"), (F.sum(F.col("mae") * F.col("width")) / F.sum("width")).alias("by_width")]
    return w.groupBy(*keys).agg(*agg) if keys else w.agg(*agg)


def relative_to(table: DataFrame, key: str, baseline: str, value: str) -> DataFrame:
    """table with `change`: the value's relative difference from the baseline row's."""
    base = table.filter(F.col(key) == baseline).select(F.col(value).alias("_base"))
    return table.crossJoin(F.broadcast(base)).withColumn("change", F.col(value) / F.col("_base") - 1).drop("_base")  # one row


def memory_variance(curve: DataFrame, spec: str, m: int) -> DataFrame:
    """curve with `mvp`: bits held, times variance."""
    return curve.withColumn("mvp", F.lit(float(SPECS[spec][0] * m)) * F.col("deviation") * F.col("deviation"))


def accuracy(simulated: DataFrame, m: int, methods: Sequence[str], keys: Sequence[str] = ()) -> DataFrame:
    """Rows (keys..., method, checkpoint, runs, mae, bias, deviation) of simulated summaries."""
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("method"), ESTIMATORS[k](F.col("cells"), m).alias("estimate")) for k in methods]))
    rows = simulated.select(*keys, "checkpoint", each.alias("x")).select(*keys, "checkpoint", "x.method", "x.estimate")
    return by_checkpoint(with_errors(rows, "checkpoint", "estimate"), [*keys, "method"])
