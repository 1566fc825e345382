"""Sketch types as projections of the level bitmap: offsets over a shared floor, history, packed words, exceptions."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from floorcount.operators.levels import registers


def with_floor(regs: DataFrame, by: Sequence[str], m: int) -> DataFrame:
    """regs with their group's floor: -1 while a register is empty. The floor's table has one row a group."""
    low = F.when(F.count(F.lit(1)) < m, F.lit(-1)).otherwise(F.min("lvl")).cast("int").alias("floor")
    floors = regs.groupBy(*by).agg(low) if by else regs.agg(low)
    if not by:
        return regs.crossJoin(F.broadcast(floors))  # one row
    keyed = floors.select(*[F.col(c).alias(f"_{c}") for c in by], "floor")
    same = F.lit(True)
    for c in by:
        same = same & F.col(c).eqNullSafe(F.col(f"_{c}"))
    return regs.join(keyed, same).drop(*[f"_{c}" for c in by])


def to_abs(levels: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """Rows (by..., reg, lvl): absolute registers."""
    return registers(levels, by).select(*by, "reg", "lvl")


def to_floor(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 4) -> DataFrame:
    """Rows (by..., reg, floor, lvl, offset, clamped): offset over the floor, at most 2^width - 1.

    While a register is empty the floor is -1 and an offset is a level plus one, so 0 always means a register at the floor.
    """
    top = (1 << width) - 1
    over = F.col("lvl") - F.col("floor")
    return with_floor(registers(levels, by).select(*by, "reg", "lvl"), by, m).select(*by, "reg", "floor", "lvl", F.least(over, F.lit(top)).alias("offset"), (over > top).alias("clamped"))


def to_hist(levels: DataFrame, by: Sequence[str] = (), h: int = 2) -> DataFrame:
    """Rows (by..., reg, lvl, state, code): absolute level with h history bits in the low end of code."""
    regs = registers(levels, by, h)
    return regs.select(*by, "reg", "lvl", "state", ((F.col("lvl") + 1) * (1 << h) + F.col("state")).alias("code"))


def to_floor_hist(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, h: int = 2, width: int = 4) -> DataFrame:
    """Rows (by..., reg, floor, offset, state, code): offset in the high bits, so codes compare as registers do."""
    top = (1 << width) - 1
    regs = with_floor(registers(levels, by, h), by, m)
    offset = F.least(F.col("lvl") - F.col("floor"), F.lit(top))
    return regs.select(*by, "reg", "floor", offset.alias("offset"), "state", (offset * (1 << h) + F.col("state")).alias("code"))


def pack(encoded: DataFrame, by: Sequence[str] = (), m: int = 2048, bits: int = 4, per_word: int = 8, code: str = "offset") -> DataFrame:
    """Rows (by..., floor, words): codes packed per_word to a word, register 0 in the low bits; empty registers are 0.

    A group's m codes meet in one row, of at most m bits * bits.
    """
    word = F.floor(F.col("reg") / per_word).cast("int").alias("word")
    shifted = F.call_function("shiftleft", F.col(code).cast("bigint"), (F.col("reg") % per_word * bits).cast("int"))
    parts = encoded.groupBy(*by, "floor", word).agg(F.bit_or(shifted).alias("bits"))
    n = -(-m // per_word)
    words = F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("held")
    held = parts.groupBy(*by, "floor").agg(words)
    filled = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.try_element_at(F.col("held"), i), F.lit(0).cast("bigint")))
    return held.select(*by, "floor", filled.alias("words"))


def unpack(packed: DataFrame, by: Sequence[str] = (), m: int = 2048, bits: int = 4, per_word: int = 8, code: str = "offset") -> DataFrame:
    """Rows (by..., reg, floor, code) of packed sketches, for registers whose code isn't 0, or all where the floor is real."""
    one = packed.select(*by, "floor", F.posexplode("words").alias("word", "bits"))
    each = one.select(*by, "floor", "word", "bits", F.explode(F.sequence(F.lit(0), F.lit(per_word - 1))).alias("k"))
    value = F.call_function("shiftright", F.col("bits"), (F.col("k") * bits).cast("int")).bitwiseAND(F.lit((1 << bits) - 1).cast("bigint")).cast("int")
    out = each.select(*by, (F.col("word") * per_word + F.col("k")).alias("reg"), "floor", value.alias(code))
    return out.filter((F.col("reg") < m) & ((F.col("floor") >= 0) | (F.col(code) > 0)))


def merge_packed(packed: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 4, per_word: int = 8) -> DataFrame:
    """Packed sketches of one group brought to the highest floor and joined by the larger register; loses what was clamped."""
    regs = unpack(packed, by, m, width, per_word)
    top = regs.select(*by, "reg", (F.col("offset") + F.col("floor")).alias("lvl"), "floor", (F.col("offset") == (1 << width) - 1).alias("clamped"))
    joined = top.groupBy(*by, "reg").agg(F.max("lvl").alias("lvl"))
    again = with_floor(joined, by, m)
    offsets = again.select(*by, "reg", "floor", F.least(F.col("lvl") - F.col("floor"), F.lit((1 << width) - 1)).alias("offset"))
    return pack(offsets, by, m, width, per_word)


def to_exceptions(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 4) -> DataFrame:
    """Rows (by..., base, n_regular, n_exceptions, exceptions): offsets over the minimum, with an exact map of those too large."""
    top = (1 << width) - 1
    rows = with_floor(registers(levels, by).select(*by, "reg", "lvl"), by, m)
    large = F.col("lvl") - F.col("floor") >= top  # the top code says: look into the map
    agg = [F.count_if(~large).alias("n_regular"), F.count_if(large).alias("n_exceptions"), F.map_from_entries(F.array_sort(F.collect_list(F.when(large, F.struct("reg", "lvl"))))).alias("exceptions")]
    return rows.groupBy(*by, F.col("floor").alias("base")).agg(*agg)


def rebase(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 3) -> DataFrame:
    """Rows (by..., base, n_exceptions): the base whose window of 2^width - 1 offsets leaves the fewest exceptions; the lowest of equals."""
    span = (1 << width) - 1
    rows = registers(levels, by).select(*by, "lvl").groupBy(*by, "lvl").agg(F.count(F.lit(1)).alias("cnt"))
    tries = rows.select(*by, "lvl", "cnt", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("base"))
    out = tries.groupBy(*by, "base").agg(F.sum(F.when((F.col("lvl") < F.col("base")) | (F.col("lvl") >= F.col("base") + span), F.col("cnt")).otherwise(0)).alias("n_exceptions"))
    best = F.min(F.struct("n_exceptions", "base")).alias("best")
    held = out.groupBy(*by).agg(best) if by else out.agg(best)
    return held.select(*by, F.col("best.base").alias("base"), F.col("best.n_exceptions").alias("n_exceptions"))


def overflow_ledger(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 3) -> DataFrame:
    """Rows (by..., t, ledger): half the registers at the top code of the present window, noted for the tier above it."""
    encoded = to_floor(levels, by, m, width)
    t = (F.col("floor") + (1 << width)).alias("t")
    return encoded.groupBy(*by, t).agg(F.floor(F.count_if(F.col("offset") == (1 << width) - 1) / 2).cast("bigint").alias("ledger"))


def repair_tiers(levels: DataFrame, by: Sequence[str] = (), m: int = 2048, width: int = 3, above: int = 6) -> DataFrame:
    """Rows (by..., t, at_least, ledger, repaired, exactly, truth): clamped registers' tiers, counted, repaired and counted again.

    at_least: registers whose stored level is t or more, summed from the top down. ledger: of the registers at the top
    code, the share that a geometric law puts at t or more, noted for each of `above` tiers over the window, as if each had
    been left by a promotion. repaired: at_least with the ledger's ghosts; exactly: differences of neighbours. truth: what the
    bitmap knows.
    """
    top = (1 << width) - 1
    regs = to_floor(levels, by, m, width)
    stored = (F.col("floor") + F.col("offset")).alias("stored")
    rows = regs.select(*by, "floor", "lvl", stored).groupBy(*by, "floor", "lvl", "stored").agg(F.count(F.lit(1)).alias("cnt"))
    tiers = rows.select(*by, "floor", "lvl", "stored", "cnt", F.explode(F.sequence(F.greatest(F.col("floor"), F.lit(0)), F.col("floor") + top + above)).alias("t"))
    over = F.col("t") - (F.col("floor") + top)
    share = F.when((over > 0) & (F.col("stored") == F.col("floor") + top), F.col("cnt")).otherwise(0)
    per = tiers.groupBy(*by, "t", over.alias("over")).agg(F.sum(F.when(F.col("stored") >= F.col("t"), F.col("cnt")).otherwise(0)).alias("at_least"), F.sum(share).alias("clamped"), F.sum(F.when(F.col("lvl") >= F.col("t"), F.col("cnt")).otherwise(0)).alias("truth"))
    ledger = F.floor(F.col("clamped") / F.pow(F.lit(2.0), F.greatest(F.col("over"), F.lit(0)))).cast("bigint")
    known = per.select(*by, "t", "at_least", ledger.alias("ledger"), "truth").withColumn("repaired", repaired(F.col("at_least"), F.col("ledger"), m))
    following = F.coalesce(F.lead("repaired").over(W.partitionBy(*by).orderBy("t")), F.lit(0.0))
    return known.withColumn("exactly", F.col("repaired") - following)


def repaired(at_least: Column, ledger: Column, m: int) -> Column:
    """Registers at or above a tier, with the ghosts of its ledger added where they don't meet a register already there."""
    return at_least + (F.lit(m) - at_least) * (1 - F.exp(-ledger / F.lit(float(m))))
