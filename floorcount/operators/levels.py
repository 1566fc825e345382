"""The level bitmap: one word a register, bit i set once level i was seen. Every sketch type is read from it.

It is built by one aggregation with a buffer of fixed width, merges by OR in any order, and adding an element twice changes
nothing. The register is part of the grouping key and comes from a hash, so a hot group is spread by itself.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from floorcount.functions import hashing as H
from floorcount.functions.estimators import HISTORY


def highest(bits: Column) -> Column:
    """Number of the highest bit that is set."""
    return F.lit(63) - H.level_of(bits)


def hashed(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str] = (), kind: str = "xxhash64") -> DataFrame:
    """Rows (by..., h) of the elements that aren't null: nothing else is read."""
    return df.select(*by, H.hash_key(cols, kind).alias("h")).filter(F.col("h").isNotNull())


def exit_shift(floor: int, hist: int = 0, mode: str = "tight") -> int:
    """How many leading zeros a hash needs to matter. paper: the floor itself; tight: one more, exact as well."""
    return max(0, (floor if mode == "paper" else floor + 1) - hist)


def passes(h: Column, floor: int, width: int, hist: int = 0, mode: str = "tight") -> Column | None:
    """The condition that a hash may still change a sketch with this floor; None where every hash may."""
    s = exit_shift(floor, hist, mode)
    return F.shiftrightunsigned(h, width - s) == 0 if s > 0 else None


#: Floors of groups, of some tens of bytes each, up to which they are sent to every task.
FEW_GROUPS = 100_000


def group_floors(rows: DataFrame, by: Sequence[str], m: int, width: int, addressing: str = "mask") -> DataFrame:
    """Rows (by..., floor) of the groups whose sketch of hashed rows has no empty register."""
    regs = levels_of(rows, by, m, width, addressing)
    low = regs.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.min(highest(F.col("bits"))).cast("int").alias("floor"))
    return low.filter(F.col("n") == m).select(*by, "floor")


def prune_by_groups(rows: DataFrame, floors: DataFrame, by: Sequence[str], width: int, hist: int = 0, mode: str = "tight", few: int | None = None) -> DataFrame:
    """Hashed rows without those that can't reach the floor of their own group, nor the hist levels under it.

    floors: rows (by..., floor), written or cheap, as they are counted first. Sent to every task while they are few;
    beyond that a join by group would cost more than the rows it saves, so all rows stay, which is as exact.
    """
    few = FEW_GROUPS if few is None else few
    if mode == "off" or floors.limit(few + 1).count() > few:
        return rows
    own = F.broadcast(floors.select(*[F.col(c).alias(f"_{c}") for c in by], "floor"))
    same = reduce(lambda a, c: a & F.col(c).eqNullSafe(F.col(f"_{c}")), by, F.lit(True))
    need = F.least(F.greatest(F.col("floor") + (0 if mode == "paper" else 1) - hist, F.lit(0)), F.lit(width))
    reached = (need == 0) | (F.call_function("shiftrightunsigned", F.col("h"), (width - need).cast("int")) == 0)
    return rows.join(own, same, "left").filter(F.coalesce(reached, F.lit(True))).drop("floor", *[f"_{c}" for c in by])


def prune_by_floor(rows: DataFrame, floor: int, width: int, hist: int = 0, mode: str = "tight") -> DataFrame:
    keep = passes(F.col("h"), floor, width, hist, mode)
    return rows if keep is None or mode == "off" else rows.filter(keep)


def levels_of(rows: DataFrame, by: Sequence[str], m: int, width: int, addressing: str = "mask") -> DataFrame:
    """Rows (by..., reg, bits) from hashed rows."""
    placed = rows.select(*by, H.register_of(F.col("h"), m, addressing).alias("reg"), H.level_of(F.col("h"), width).alias("lvl"))
    return placed.groupBy(*by, "reg").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("lvl"))).alias("bits"))


def build_levels(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str] = (), m: int = 2048, kind: str = "xxhash64", addressing: str = "mask") -> DataFrame:
    """Rows (by..., reg, bits): at most m a group. Null elements are skipped, null groups are groups."""
    return levels_of(hashed(df, cols, by, kind), by, m, H.WIDTH[kind], addressing)


def pilot_floor(rows: DataFrame, m: int, width: int, addressing: str = "mask") -> int:
    """The floor of one ungrouped sketch of rows: one number to the driver."""
    regs = levels_of(rows, (), m, width, addressing)
    row = regs.agg(F.count(F.lit(1)).alias("n"), F.min(highest(F.col("bits"))).alias("low")).first()
    return row["low"] if row["n"] == m else -1


def build_levels_pruned(df: DataFrame, cols: Sequence[str | Column], pilot: DataFrame, m: int = 2048, kind: str = "xxhash64", addressing: str = "mask", hist: int = HISTORY, mode: str = "paper", by: Sequence[str] = ()) -> DataFrame:
    """build_levels(), where a pilot part of df (a few files, a day) has shown how high each floor is at least.

    Rows that can't reach the floor, nor the hist levels under it, are dropped before the aggregation. A part's floor never
    exceeds the whole's, and every register's largest level is kept: floor, offsets and hist history bits are exact. The
    tight bound spares one level more, which only a sketch that holds the pilot already can do without. The
    pilot should be a hundredth of df or so: it is read once more. Without groups its floor is one number; with groups,
    each has its own, and groups that the pilot hasn't filled aren't pruned.
    """
    width = H.WIDTH[kind]
    first, rows = hashed(pilot, cols, by, kind), hashed(df, cols, by, kind)
    if by:
        return levels_of(prune_by_groups(rows, group_floors(first, by, m, width, addressing), by, width, hist, mode), by, m, width, addressing)
    floor = pilot_floor(first, m, width, addressing)
    return levels_of(prune_by_floor(rows, floor, width, hist, mode), (), m, width, addressing)


def build_micro(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str] = (), m: int = 2048, kind: str = "xxhash64") -> DataFrame:
    """Rows (by..., micro): a bitmap of 64 places for small sets."""
    rows = hashed(df, cols, by, kind)
    word = F.bit_or(F.call_function("shiftleft", F.lit(1).cast("bigint"), H.micro_place(F.col("h"), m))).alias("micro")
    return rows.groupBy(*by).agg(word) if by else rows.agg(F.coalesce(word, F.lit(0).cast("bigint")).alias("micro"))


def build_lazy(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str], m: int = 2048, least: int = 24, kind: str = "xxhash64", few: int = FEW_GROUPS) -> tuple[DataFrame, DataFrame]:
    """(rows (by..., micro, allocated), rows (by..., reg, bits)): registers only for groups whose small bitmap holds `least` places or more.

    Most groups of a long tail stay a single word. The allocated ones pick their rows by a join, sent to all tasks while few.
    """
    micro = build_micro(df, cols, by, m, kind).withColumn("allocated", F.bit_count("micro") >= least)
    large = micro.filter("allocated").select(*[F.col(c).alias(f"_{c}") for c in by])
    send = F.broadcast if large.limit(few + 1).count() <= few else (lambda x: x)
    same = reduce(lambda a, c: a & F.col(c).eqNullSafe(F.col(f"_{c}")), by, F.lit(True))
    return micro, levels_of(hashed(df, cols, by, kind).join(send(large), same, "left_semi"), by, m, H.WIDTH[kind])


def registers(levels: DataFrame, by: Sequence[str] = (), h: int = HISTORY) -> DataFrame:
    """Rows (by..., reg, lvl, state): the largest level and the h bits under it."""
    lvl = highest(F.col("bits"))
    both = levels.select(*by, "reg", "bits", lvl.cast("int").alias("lvl"))
    down = F.call_function("shiftright", F.col("bits"), F.greatest(F.col("lvl") - h, F.lit(0)))
    up = F.call_function("shiftleft", down, F.greatest(F.lit(h) - F.col("lvl"), F.lit(0)))
    return both.select(*by, "reg", "lvl", up.bitwiseAND(F.lit((1 << h) - 1).cast("bigint")).cast("int").alias("state"))


def summarize(levels: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """Rows (by..., cells): the summary that estimates are made of. One row, with no cells, for an empty table without groups."""
    counted = registers(levels, by).groupBy(*by, "lvl", "state").agg(F.count(F.lit(1)).alias("cnt"))
    cells = F.array_sort(F.collect_list(F.struct("lvl", "state", "cnt"))).alias("cells")
    return counted.groupBy(*by).agg(cells) if by else counted.agg(cells)


def fractional_registers(df: DataFrame, cols: Sequence[str | Column], by: Sequence[str] = (), m: int = 2048, q: int = 2, kind: str = "xxhash64", addressing: str = "mask") -> DataFrame:
    """Rows (by..., reg, code): registers that hold q bits of a level's fraction, code being level * 2^q and the fraction.

    The bits after a hash's leading one say how near it is to the next level: all ones are the least rare. The largest code
    is kept. An estimator for these registers isn't part of this library.
    """
    h, width = F.col("h"), H.WIDTH[kind]
    lvl = H.level_of(h, width)
    placed = hashed(df, cols, by, kind).select(*by, "h", H.register_of(h, m, addressing).alias("reg"), lvl.alias("lvl"))
    after = F.call_function("shiftright", h, F.greatest(F.lit(width - 1 - q) - F.col("lvl"), F.lit(0))).bitwiseAND(F.lit((1 << q) - 1).cast("bigint"))
    code = (F.col("lvl") * (1 << q) + ((1 << q) - 1) - after).cast("int")
    return placed.select(*by, "reg", code.alias("code")).groupBy(*by, "reg").agg(F.max("code").alias("code"))


def merge_levels(*parts: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """The bitmaps of all parts together, without loss."""
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out.groupBy(*by, "reg").agg(F.bit_or("bits").alias("bits"))
