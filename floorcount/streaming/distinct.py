"""Distinct counts over event-time windows of a stream."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from floorcount.functions import hashing as H
from floorcount.functions.estimators import est_tlc
from floorcount.operators.levels import registers


def windowed_levels(events: DataFrame, cols: Sequence[str], m: int, window: Column, by: Sequence[str] = (), kind: str = "xxhash64") -> DataFrame:
    """Rows (window, by..., reg, bits): state of at most m words for each open window and group."""
    h = H.hash_key(cols, kind)
    placed = events.withColumn("h", h).filter(F.col("h").isNotNull()).select(window.alias("window"), *by, H.register_of(F.col("h"), m).alias("reg"), H.level_of(F.col("h"), H.WIDTH[kind]).alias("lvl"))
    return placed.groupBy("window", *by, "reg").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("lvl"))).alias("bits"))


def windowed_estimates(events: DataFrame, cols: Sequence[str], m: int = 256, size: str = "1 hour", slide: str | None = None, by: Sequence[str] = (), time: str = "ts", kind: str = "xxhash64", tool: Callable = est_tlc) -> DataFrame:
    """Rows (window, by..., estimate) once a window has closed; the same for batches, where all are closed."""
    levels = windowed_levels(events, cols, m, F.window(time, size, slide or size), by, kind)
    regs = registers(levels, ["window", *by])
    # cells of a window are few, so one more aggregation of registers gives them: a list of at most m
    cells = regs.groupBy("window", *by).agg(F.array_sort(F.collect_list(F.struct("lvl", "state", F.lit(1).cast("bigint").alias("cnt")))).alias("cells"))
    return cells.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *by, tool(F.col("cells"), m).alias("estimate"))


def write_estimates(estimates: DataFrame, path: str, checkpoint: str):
    """A query that appends closed windows to Parquet, each once."""
    return estimates.writeStream.outputMode("append").option("checkpointLocation", checkpoint).format("parquet").option("path", path)


def upsert_totals(levels: DataFrame, merge: Callable[[DataFrame, int], None], checkpoint: str):
    """A query that hands each micro-batch's bitmaps to merge(df, batch_id); bitmaps OR, so a replayed batch does no harm."""
    return levels.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(merge)


def sequential_state(events: DataFrame, key: str, col: str, m: int = 256, kind: str = "xxhash64") -> DataFrame:
    """Rows (key, rows, floor, estimate) after each micro-batch, from an order-dependent sketch kept for each key."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    rows = events.select(F.col(key).cast("string").alias("k"), H.hash_key([col], kind).alias("h")).filter(F.col("h").isNotNull())

    def step(k: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        from floorcount.operators.state import FloorSketch

        sketch = FloorSketch.from_bytes(state.get[0]) if state.exists else FloorSketch(m=m)
        for pdf in batches:
            sketch.add_batch(pdf["h"].to_numpy().astype(np.int64).view(np.uint64), H.WIDTH[kind])
        state.update((sketch.to_bytes(),))
        z = m - float(sketch.at_least()[sketch.floor + 1])
        yield pd.DataFrame({"k": [k[0]], "rows": [sketch.rows], "floor": [sketch.floor], "estimate": [2.0 ** (sketch.floor + 1) * m * float(np.log(m / max(z, 0.5)))]})

    return rows.groupBy("k").applyInPandasWithState(step, "k string, rows long, floor int, estimate double", "sketch binary", "update", GroupStateTimeout.NoTimeout)
