"""Simulated streams and growing tables: register summaries at checkpoints, for each run. A run's numbers depend on its seed, and on the table, alone."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from floorcount.operators import levels
from floorcount.operators.state import FloorSketch, TruncatedOffset, TwoBit, levels_of

CELLS = "array<struct<lvl: int, state: int, cnt: bigint>>"


def checkpoints(largest: int, step: float = 1.01) -> list[int]:
    """From 1 on, each at least one more and `step` times the one before."""
    out, c = [], 1
    while c <= largest:
        out.append(c)
        c = max(c + 1, int(step * c))
    return out


def _cells(bits: np.ndarray) -> list[dict]:
    """Summary of level bitmaps."""
    full = bits > 0
    b = bits[full]
    x = b.copy()
    for k in (1, 2, 4, 8, 16, 32):
        x |= x >> np.uint64(k)
    lvl = np.bitwise_count(x).astype(np.int64) - 1
    state = np.zeros(len(b), dtype=np.int64)
    for d in (1, 2, 3):
        state |= np.where(lvl >= d, (b >> np.maximum(lvl - d, 0).astype(np.uint64)) & np.uint64(1), np.uint64(0)).astype(np.int64) << (3 - d)
    key, count = np.unique(lvl * 8 + state, return_counts=True)
    return [{"lvl": int(k) >> 3, "state": int(k) & 7, "cnt": int(c)} for k, c in zip(key, count)]


def simulate_unique(spark: SparkSession, runs: int, m: int = 2048, points: Sequence[int] = (), seed: int = 1, parts: int | None = None) -> DataFrame:
    """Rows (run, checkpoint, cells): sketches of all-distinct streams.

    Level i of a register is first met after an exponential time with mean m * 2^(i+1) elements, independently of the others, so a
    run draws these times once and reads off every checkpoint; small checkpoints, where the count of elements must be exact, hash that many.
    """
    points = list(points) or checkpoints(1 << 20, 1.2)
    exact = 1 << 13

    def one(run: int) -> Iterator[dict]:
        rng = np.random.default_rng([seed, run])
        few = [c for c in points if c <= exact]
        if few:
            h = rng.integers(0, 1 << 63, max(few), dtype=np.uint64) << np.uint64(1) | rng.integers(0, 2, max(few), dtype=np.uint64)
            reg = ((h & np.uint64(0xFFFFFFFF)) % np.uint64(m)).astype(np.int64)
            x = h.copy()
            for k in (1, 2, 4, 8, 16, 32):
                x |= x >> np.uint64(k)
            bit = np.uint64(1) << np.minimum(64 - np.bitwise_count(x).astype(np.uint64), np.uint64(63))
            bits, at = np.zeros(m, dtype=np.uint64), 0
            for c in few:
                np.bitwise_or.at(bits, reg[at:c], bit[at:c])
                at = c
                yield {"run": run, "checkpoint": c, "cells": _cells(bits)}
        many = [c for c in points if c > exact]
        if many:
            depth = min(63, int(np.log2(max(many) / m + 1)) + 24)
            times = rng.exponential(1.0, (depth, m)) * (m * 2.0 ** np.arange(1, depth + 1))[:, None]
            for c in many:
                met = times <= c
                bits = np.zeros(m, dtype=np.uint64)
                for i in range(depth):
                    bits |= met[i].astype(np.uint64) << np.uint64(i)
                yield {"run": run, "checkpoint": c, "cells": _cells(bits)}

    return _rows(spark, runs, parts, one, f"run long, checkpoint long, cells {CELLS}")


def grown(elements: DataFrame, runs: int, m: int = 2048, points: Sequence[float] = (), seed: int = 1) -> DataFrame:
    """Rows (run, checkpoint, cells): sketches of a growing table, whose elements are hashed anew for each run.

    elements: one column; null is none. points: in proportion, the last one being the whole table; a hash of its own tells which
    elements have come by a point. checkpoint: how many distinct ones these are, counted; points without any are left out.
    A task holds runs x points x m bitmaps, and that many at most are shuffled by each, whatever the table's size.
    """
    (name,) = elements.columns
    shares, k = [p / max(points) for p in sorted(points)], len(points)
    place = F.shiftrightunsigned(F.xxhash64(F.lit("place"), name), 11) / F.lit(2.0**53)
    step = sum([(place >= F.lit(s)).cast("int") for s in shares[:-1]], F.lit(0))
    dealt = elements.filter(F.col(name).isNotNull()).distinct().select(F.xxhash64(name).alias("h"), step.alias("step"))
    salts = np.random.default_rng(seed).integers(0, 1 << 64, runs, dtype=np.uint64)

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        bits = np.zeros((runs, k * m), dtype=np.uint64)
        for pdf in batches:
            h, at = pdf["h"].to_numpy().view(np.uint64), pdf["step"].to_numpy().astype(np.int64) * m
            for run in range(runs):
                x = _mix(h ^ salts[run])
                np.bitwise_or.at(bits[run], at + ((x & np.uint64(0xFFFFFFFF)) % np.uint64(m)).astype(np.int64), np.uint64(1) << levels_of(x).astype(np.uint64))
        bits = np.bitwise_or.accumulate(bits.reshape(runs, k, m), axis=1)
        for run in range(runs):
            reg = np.flatnonzero(bits[run, -1])
            yield pd.DataFrame({"run": np.int64(run), "reg": reg.astype(np.int32), **{f"s{i}": bits[run, i, reg].view(np.int64) for i in range(k)}})

    made = dealt.mapInPandas(work, ", ".join(["run long, reg int", *(f"s{i} long" for i in range(k))]))
    whole = made.groupBy("run", "reg").agg(*[F.bit_or(f"s{i}").alias(f"s{i}") for i in range(k)])
    each = whole.select("run", "reg", F.posexplode(F.array(*[f"s{i}" for i in range(k)])).alias("step", "bits")).filter("bits != 0")
    come = dealt.agg(F.array(*[F.count_if(F.col("step") <= i) for i in range(k)]).alias("come"))  # one row
    return levels.summarize(each, ["run", "step"]).crossJoin(F.broadcast(come)).select("run", F.get("come", F.col("step")).alias("checkpoint"), "cells")


def _rows(spark: SparkSession, runs: int, parts: int | None, one, schema: str) -> DataFrame:
    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for run in pdf["id"]:
                yield pd.DataFrame(list(one(int(run))))

    return spark.range(0, runs, 1, parts or min(runs, spark.sparkContext.defaultParallelism)).mapInPandas(work, schema)


SEQUENTIAL = {
    "floor4": lambda m: FloorSketch(m, 4), "floor3": lambda m: FloorSketch(m, 3), "floor5": lambda m: FloorSketch(m, 5), "fhist5": lambda m: FloorSketch(m, 4, 1),
    "fhist6": lambda m: FloorSketch(m, 4, 2), "fhist7": lambda m: FloorSketch(m, 4, 3), "abs6": lambda m: FloorSketch(m, 6, exit_mode="off"), "hist8": lambda m: FloorSketch(m, 6, 2, "off"),
    "offset4_trunc": TruncatedOffset,
}


def draws(rng: np.random.Generator, n: int, adds: int) -> np.ndarray:
    """Indexes below n, drawn with a lean to the small ones: the smaller of two."""
    return np.minimum(rng.integers(0, n, adds), rng.integers(0, n, adds))


def simulate_skewed(spark: SparkSession, runs: int, specs: Sequence[str] = ("floor4", "floor3"), m: int = 256, n: int = 100_000, passes: int = 8, points: Sequence[int] = (), seed: int = 1, repair: bool = True, parts: int | None = None, at_end: bool = False) -> DataFrame:
    """Rows (run, spec, checkpoint, truth, adds, cells, repaired): order-dependent sketches of duplicate-heavy streams.

    Elements are pairs out of two arrays of sqrt(n) words; a bitmap tells how many distinct ones have come. `repaired` is the
    summary after the ledger's repair; the same as cells where there is none. All passes are run; at_end adds a row for each
    sketch at the stream's end, as checkpoint n, whatever the truth is by then.
    """
    side = int(np.ceil(np.sqrt(n)))
    points = sorted(points or checkpoints(n, 1.3))
    make = {k: SEQUENTIAL[k] for k in specs}

    def one(run: int) -> Iterator[dict]:
        rng = np.random.default_rng([seed, run])
        upper, lower = rng.integers(0, 1 << 32, side, dtype=np.uint64), rng.integers(0, 1 << 32, side, dtype=np.uint64)
        seen, truth, adds, due = np.zeros(side * side, dtype=bool), 0, 0, 0
        held = {k: f(m) for k, f in make.items()}

        def told(k: str, s, checkpoint: int, true: int, added: int) -> dict:
            cells = [dict(zip(("lvl", "state", "cnt"), c)) for c in s.cells()]
            fixed = [{"lvl": a, "state": b, "cnt": int(round(c))} for a, b, c in s.repaired_cells()] if repair and isinstance(s, FloorSketch) and s.ledger and s.width == 3 else cells
            return {"run": run, "spec": k, "checkpoint": checkpoint, "truth": true, "adds": added, "cells": cells, "repaired": fixed}

        while adds < n * passes:
            i = draws(rng, n, 4096)
            fresh = np.zeros(len(i), dtype=bool)
            fresh[np.unique(i, return_index=True)[1]] = True
            fresh &= ~seen[i]
            count = truth + np.cumsum(fresh)
            start = 0
            while due < len(points) and count[-1] >= points[due]:
                stop = int(np.searchsorted(count, points[due])) + 1
                for s in held.values():
                    s.add_batch(_mix(upper[i[start:stop] // side] << np.uint64(32) | lower[i[start:stop] % side]))
                for k, s in held.items():
                    yield told(k, s, points[due], points[due], adds + stop)
                start, due = stop, due + 1
            for s in held.values():
                s.add_batch(_mix(upper[i[start:] // side] << np.uint64(32) | lower[i[start:] % side]))
            seen[i] = True
            truth, adds = int(count[-1]), adds + len(i)
        if at_end:
            yield from (told(k, s, n, truth, adds) for k, s in held.items())

    return _rows(spark, runs, parts, one, f"run long, spec string, checkpoint long, truth long, adds long, cells {CELLS}, repaired {CELLS}")


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def simulate_types(spark: SparkSession, runs: int, m: int = 2048, points: Sequence[int] = (), seed: int = 1, parts: int | None = None) -> DataFrame:
    """Rows (run, spec, checkpoint, cells, own): every sketch type fed the same distinct hashes; own: the type's own estimate where it has one.

    Registers with an exception map hold every level, as absolute ones do, whatever the width of the regular ones.
    """
    points = list(points) or checkpoints(100_000, 2.0)

    def one(run: int) -> Iterator[dict]:
        rng = np.random.default_rng([seed, run])
        h = rng.integers(0, 1 << 64, max(points), dtype=np.uint64)
        held = {k: f(m) for k, f in SEQUENTIAL.items()}
        two, at = TwoBit(m), 0
        for c in points:
            for k, s in held.items():
                s.add_batch(h[at:c])
                cells = [dict(zip(("lvl", "state", "cnt"), x)) for x in s.cells()]
                for spec in (k, *(("offset4_map", "offset3_map") if k == "abs6" else ())):
                    yield {"run": run, "spec": spec, "checkpoint": c, "cells": cells, "own": s.estimate() if isinstance(s, TruncatedOffset) else None}
            two.add_batch(h[at:c])
            yield {"run": run, "spec": "twobit", "checkpoint": c, "cells": [], "own": two.estimate()}
            at = c

    return _rows(spark, runs, parts, one, f"run long, spec string, checkpoint long, cells {CELLS}, own double")


def merge_study(spark: SparkSession, runs: int, m: int = 2048, n: int = 200_000, parts_of: Sequence[int] = (1, 8, 16, 64), seed: int = 1, width: int = 4) -> DataFrame:
    """Rows (run, parts, truth, clamped, lost, cells): one stream dealt to so many sketches, merged one after the other.

    clamped: registers of the merged sketch at the top code. lost: levels that the merged sketch is short of, over all
    registers, of those of one bitmap of the whole stream.
    """

    def one(run: int) -> Iterator[dict]:
        h = np.random.default_rng([seed, run]).integers(0, 1 << 64, n, dtype=np.uint64)
        true = np.full(m, -1, dtype=np.int64)
        np.maximum.at(true, (h & np.uint64(m - 1)).astype(np.int64), levels_of(h))
        for k in parts_of:
            whole = None
            for i in range(k):
                s = FloorSketch(m, width).add_batch(h[i::k])
                whole = s if whole is None else whole.merge(s)
            now = whole.levels()
            top = int(np.count_nonzero(now >= whole.floor + whole.top))
            yield {"run": run, "parts": k, "truth": n, "clamped": top, "lost": int((true - now).clip(min=0).sum()), "cells": [dict(zip(("lvl", "state", "cnt"), x)) for x in whole.cells()]}

    return _rows(spark, runs, None, one, f"run long, parts int, truth long, clamped int, lost long, cells {CELLS}")


def _streams(rows: DataFrame, runs: int) -> DataFrame:
    """Rows (run, ord, h, fresh), those of a run in one task and in the order of ord: a stream that depends on its order can't be cut."""
    return rows.repartition(4 * runs, "run").sortWithinPartitions("run", "ord", "fresh")


def _chunks(batches: Iterator[pd.DataFrame], size: int = 1 << 18) -> Iterator[tuple[int, np.ndarray, np.ndarray, bool]]:
    """(run, h, fresh, whether the run ends) by some rows at a time."""
    held: list[pd.DataFrame] = []
    for pdf in batches:
        for run, part in pdf.groupby("run", sort=False):
            if held and (held[0]["run"].iat[0] != run or sum(map(len, held)) >= size):
                yield _chunk(held, held[0]["run"].iat[0] != run)
                held = []
            held.append(part)
    if held:
        yield _chunk(held, True)


def _chunk(held: list[pd.DataFrame], ends: bool) -> tuple[int, np.ndarray, np.ndarray, bool]:
    whole = pd.concat(held)
    return int(whole["run"].iat[0]), whole["h"].to_numpy().view(np.uint64), whole["fresh"].to_numpy().astype(bool), ends


def _of_runs(elements: DataFrame, runs: int, *order: str) -> DataFrame:
    """Rows (run, ord, h): each element once for each run, with its place in the run's order."""
    name = elements.columns[0]
    each = elements.filter(F.col(name).isNotNull()).select("*", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(runs - 1).cast("bigint"))).alias("run"))
    return each.select("run", F.xxhash64(F.lit("place"), "run", name, *order).alias("ord"), F.xxhash64(name).alias("h"))


def merge_dealt(elements: DataFrame, runs: int, m: int = 2048, parts_of: Sequence[int] = (1, 8, 16, 64), seed: int = 1, widths: Sequence[int] = (4,)) -> DataFrame:
    """merge_study() of a table's distinct elements: rows (run, width, parts, truth, clamped, lost, cells). elements: one column.

    Each run has them in another order, and hashed anew. A task holds the sketches of one run.
    """
    salts = np.random.default_rng(seed).integers(0, 1 << 64, runs, dtype=np.uint64)

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict = {}
        for run, h, _, ends in _chunks(batches):
            if not held:
                held = {(w, k): [FloorSketch(m, w) for _ in range(k)] for w in widths for k in parts_of}
                true, n = np.full(m, -1, dtype=np.int64), 0
            x = _mix(h ^ salts[run])
            np.maximum.at(true, (x & np.uint64(m - 1)).astype(np.int64), levels_of(x))
            for (_, k), dealt in held.items():
                for i, s in enumerate(dealt):
                    s.add_batch(x[(i - n) % k :: k])
            n += len(x)
            if ends:
                for (w, k), dealt in held.items():
                    whole = dealt[0]
                    for s in dealt[1:]:
                        whole = whole.merge(s)
                    now = whole.levels()
                    cells = [dict(zip(("lvl", "state", "cnt"), c)) for c in whole.cells()]
                    yield pd.DataFrame([{"run": run, "width": w, "parts": k, "truth": n, "clamped": int(np.count_nonzero(now >= whole.floor + whole.top)), "lost": int((true - now).clip(min=0).sum()), "cells": cells}])
                held = {}

    rows = _of_runs(elements.distinct(), runs).withColumn("fresh", F.lit(True))
    return _streams(rows, runs).mapInPandas(work, f"run long, width int, parts int, truth long, clamped int, lost long, cells {CELLS}")


def repeated(elements: DataFrame, runs: int, specs: Sequence[str] = ("floor4", "floor3"), m: int = 256, points: Sequence[float] = (), seed: int = 1) -> DataFrame:
    """simulate_skewed() of a table's rows with all their repeats: rows (run, spec, checkpoint, truth, adds, cells, repaired).

    elements: the elements, and the columns that tell their rows apart. points: distinct elements in proportion, the last one
    being all of them at the stream's end. Each run has the rows in another order, hashed anew; markers, one a distinct element,
    are sorted in where it first comes, so no task has to remember what it has seen.
    """
    name, *order = elements.columns
    total = elements.agg(F.count_distinct(name)).first()[0]
    due_at = sorted({max(1, round(p / max(points) * total)) for p in points} - {total})
    salts = np.random.default_rng(seed).integers(0, 1 << 64, runs, dtype=np.uint64)

    def work(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict = {}

        def told(run: int, checkpoint: int) -> pd.DataFrame:
            out = []
            for k, s in held.items():
                cells = [dict(zip(("lvl", "state", "cnt"), c)) for c in s.cells()]
                fixed = [{"lvl": a, "state": b, "cnt": int(round(c))} for a, b, c in s.repaired_cells()] if isinstance(s, FloorSketch) and s.ledger and s.width == 3 else cells
                out.append({"run": run, "spec": k, "checkpoint": checkpoint, "truth": checkpoint, "adds": s.rows, "cells": cells, "repaired": fixed})
            return pd.DataFrame(out)

        for run, h, fresh, ends in _chunks(batches):
            if not held:
                held, truth, due = {k: SEQUENTIAL[k](m) for k in specs}, 0, 0
            x, count, start = _mix(h ^ salts[run]), truth + np.cumsum(fresh), 0
            while due < len(due_at) and count[-1] >= due_at[due]:
                stop = int(np.searchsorted(count, due_at[due])) + 1
                for s in held.values():
                    s.add_batch(x[start:stop][~fresh[start:stop]])
                yield told(run, due_at[due])
                start, due = stop, due + 1
            for s in held.values():
                s.add_batch(x[start:][~fresh[start:]])
            truth = int(count[-1])
            if ends:
                yield told(run, truth)
                held = {}

    rows = _of_runs(elements, runs, *order)
    first = rows.groupBy("run", "h").agg(F.min("ord").alias("ord")).select("run", "ord", "h", F.lit(True).alias("fresh"))
    return _streams(rows.withColumn("fresh", F.lit(False)).unionByName(first), runs).mapInPandas(work, f"run long, spec string, checkpoint long, truth long, adds long, cells {CELLS}, repaired {CELLS}")


def build_cf(simulated: DataFrame, m: int, tool, ratio_of_means: bool = False) -> DataFrame:
    """Rows (checkpoint, raw, factor): the mean of true over estimate, or true over the mean estimate."""
    est = tool(F.col("cells"), m)
    each = simulated.select("checkpoint", est.alias("raw"))
    factor = F.first("checkpoint") / F.avg("raw") if ratio_of_means else F.avg(F.col("checkpoint") / F.col("raw"))
    return each.groupBy("checkpoint").agg(F.avg("raw").alias("raw"), factor.alias("factor"))
