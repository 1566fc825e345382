"""Hashes of elements, and what a register sketch reads from them: register, level, place in the small-set bitmap."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Bits of each kind of hash. md5_60 has the same values in other SQL engines; xxhash64 is the fast one.
WIDTH = {"xxhash64": 64, "md5_60": 60, "mix64": 64}
NULL = "-"


def element(cols: Sequence[str | Column]) -> Column:
    """One column as it is; several as one text that no other tuple makes: each part after its length, null as a mark. Null only if all are."""
    columns = [F.col(c) if isinstance(c, str) else c for c in cols]
    if len(columns) == 1:
        return columns[0]
    told = lambda c: F.coalesce(F.concat(F.length(c).cast("string"), F.lit(":"), c), F.lit(NULL))
    texts = [c.cast("string") for c in columns]
    return F.when(F.coalesce(*texts).isNotNull(), F.concat(*map(told, texts)))


def _half_sum(a: Column, b: Column) -> Column:
    """a + b modulo 2^64, with additions that can't overflow."""
    low = a.bitwiseAND(F.lit(0xFFFFFFFF)) + b.bitwiseAND(F.lit(0xFFFFFFFF))
    high = F.shiftrightunsigned(a, 32) + F.shiftrightunsigned(b, 32) + F.shiftrightunsigned(low, 32)
    return F.shiftleft(high, 32).bitwiseOR(low.bitwiseAND(F.lit(0xFFFFFFFF)))


def _with(x: Column, step) -> Column:
    """step(x), with x computed once however often step uses it."""
    return F.get(F.transform(F.array(x), step), 0)


def mix64(x: Column) -> Column:
    """A 64-bit integer mixer of shifts, sums and exclusive ors, free of overflow errors."""
    add = lambda *shifts: lambda v: reduce(lambda s, k: _half_sum(s, F.shiftleft(v, k)), shifts, v)
    fold = lambda k: lambda v: v.bitwiseXOR(F.shiftrightunsigned(v, k))
    first = lambda v: _half_sum(F.bitwise_not(v), F.shiftleft(v, 21))
    return reduce(_with, (first, fold(24), add(3, 8), fold(14), add(2, 4), fold(28), add(31)), x.cast("bigint"))


def hash_key(cols: Sequence[str | Column], kind: str = "xxhash64") -> Column:
    """The hash of an element as bigint; null for null elements, which no sketch counts."""
    e = element(cols)
    if kind == "xxhash64":
        made = F.xxhash64(e)
    elif kind == "md5_60":
        made = F.conv(F.substring(F.md5(e.cast("string").cast("binary")), 1, 15), 16, 10).cast("bigint")
    elif kind == "mix64":
        made = mix64(e)
    else:
        raise ValueError(f"no hash {kind}")
    return F.when(e.isNotNull(), made)


def register_of(h: Column, m: int, addressing: str = "mask") -> Column:
    """mask: the low bits, for a power of two; mod: the low 32 bits modulo m, for any m."""
    if addressing == "mask":
        if m & (m - 1):
            raise ValueError("mask addressing needs a power of two")
        return h.bitwiseAND(F.lit(m - 1).cast("bigint")).cast("int")
    return F.pmod(h.bitwiseAND(F.lit(0xFFFFFFFF).cast("bigint")), F.lit(m).cast("bigint")).cast("int")


def level_of(h: Column, width: int = 64) -> Column:
    """Leading zeros of a hash of `width` bits: the highest one is smeared down and counted, no logarithm."""
    smeared = h
    for k in (1, 2, 4, 8, 16, 32):
        smeared = smeared.bitwiseOR(F.shiftrightunsigned(smeared, k))
    return F.least(F.lit(width) - F.bit_count(smeared), F.lit(63)).cast("int")


def micro_place(h: Column, m: int) -> Column:
    """Six bits above the register selector."""
    return F.shiftrightunsigned(h, max(1, (m - 1).bit_length())).bitwiseAND(F.lit(63).cast("bigint")).cast("int")
