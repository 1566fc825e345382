"""Sketches whose result depends on the order of what they see: NumPy state, fed in batches.

Batches act as if their hashes came one by one. Between two events that depend on the order (a floor that rises, a
threshold that moves) registers only take maxima, so a batch is cut at these events and its pieces are taken at once.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame

from floorcount.operators.levels import hashed


def levels_of(h: np.ndarray, width: int = 64) -> np.ndarray:
    """Leading zeros of unsigned hashes of `width` bits."""
    x = h.astype(np.uint64, copy=True)
    for k in (1, 2, 4, 8, 16, 32):
        x |= x >> np.uint64(k)
    return np.minimum(width - np.bitwise_count(x).astype(np.int64), 63)


MODES = ("tight", "paper", "off")
HEAD = struct.Struct("<iiiBiiQqqqqi?")


@dataclass
class FloorSketch:
    """Offsets of `width` bits over a shared floor, with `hist` history bits, an exit test, promotion and, for repair, a ledger."""

    m: int = 2048
    width: int = 4
    hist: int = 0
    exit_mode: str = "tight"
    lazy: int = 0
    floor: int = -1
    micro: int = 0
    rows: int = 0
    passed: int = 0
    updates: int = 0
    promotions: int = 0
    scanned: int = 0
    ledger: dict[int, int] = field(default_factory=dict)
    bits: np.ndarray | None = None

    @property
    def top(self) -> int:
        return (1 << self.width) - 1

    def _bits(self) -> np.ndarray:
        if self.bits is None:
            self.bits = np.zeros(self.m, dtype=np.uint64)
        return self.bits

    def levels(self) -> np.ndarray:
        """Stored level of each register, -1 where empty."""
        return 63 - levels_of(self._bits()) - (self._bits() == 0)

    def add_batch(self, h: np.ndarray, width: int = 64) -> FloorSketch:
        h = h.astype(np.uint64, copy=False)
        self.rows += len(h)
        k = max(1, (self.m - 1).bit_length())
        if self.micro != (1 << 64) - 1:
            places = (h >> np.uint64(k)) & np.uint64(63)
            self.micro |= int(np.bitwise_or.reduce(np.uint64(1) << places)) if len(h) else 0
        if self.lazy and self.bits is None and self.micro.bit_count() < self.lazy:
            return self  # the small bitmap alone, as yet
        reg = (h & np.uint64(self.m - 1)).astype(np.int64) if not self.m & (self.m - 1) else ((h & np.uint64(0xFFFFFFFF)) % np.uint64(self.m)).astype(np.int64)
        lvl = levels_of(h, width)
        while len(lvl):
            if self.exit_mode != "off":
                least = (max(0, self.floor) if self.exit_mode == "paper" else self.floor + 1) - self.hist
                keep = lvl >= least
                reg, lvl = reg[keep], lvl[keep]
            now = self.levels()
            at_floor = now == self.floor
            hit = np.flatnonzero(at_floor[reg] & (lvl > self.floor))
            which, first = np.unique(reg[hit], return_index=True)
            ends = len(which) == int(at_floor.sum())  # the batch promotes
            upto = int(hit[first].max()) + 1 if ends and len(which) else len(lvl)
            self._take(reg[:upto], lvl[:upto], now)
            reg, lvl = reg[upto:], lvl[upto:]
            if ends:
                self._promote()
        return self

    def _take(self, reg: np.ndarray, lvl: np.ndarray, now: np.ndarray) -> None:
        self.passed += len(lvl)
        stored = np.minimum(lvl, self.floor + self.top)
        # a history bit below what a register can still report is lost, as it would be in the packed register
        seen = stored >= now[reg] - self.hist if self.hist else stored > now[reg]
        self.updates += self._changes(reg[seen], stored[seen], now)
        np.bitwise_or.at(self._bits(), reg[seen], np.uint64(1) << stored[seen].astype(np.uint64))

    def _changes(self, reg: np.ndarray, stored: np.ndarray, now: np.ndarray) -> int:
        """How many of these, one by one, change a register: its largest level, or a history bit that it can report and hasn't."""
        if not len(reg):
            return 0
        order = np.argsort(reg, kind="stable")
        reg, stored = reg[order], stored[order]
        held = np.maximum.accumulate(reg * 128 + np.maximum(stored, now[reg]) + 1)  # the running largest of each register
        first = np.concatenate([[True], reg[1:] != reg[:-1]])
        before = np.where(first, now[reg], np.concatenate([[0], held[:-1] - reg[:-1] * 128 - 1]))
        raised = stored > before
        if not self.hist:
            return int(np.count_nonzero(raised))
        unset = (self._bits()[reg] >> stored.astype(np.uint64)) & np.uint64(1) == 0
        fresh = np.zeros(len(reg), dtype=bool)
        can = np.flatnonzero(unset & (stored >= before - self.hist))
        fresh[can[np.unique(reg[can] * 64 + stored[can], return_index=True)[1]]] = True
        return int(np.count_nonzero(fresh))

    def _promote(self) -> None:
        while True:
            now = self.levels()
            self.scanned += self.m
            if now.min() <= self.floor:
                return
            if self.floor >= 0 or now.min() >= 0:
                clamped = int(np.count_nonzero(now >= self.floor + self.top))
                self.ledger[self.floor + self.top + 1] = clamped // 2
            self.floor += 1
            self.promotions += 1

    def cells(self) -> list[tuple[int, int, int]]:
        """(lvl, state of three bits, cnt), as a summary of the level bitmap has them."""
        now = self.levels()
        full = now >= 0
        lvl, bits = now[full], self._bits()[full]
        state = np.zeros(len(lvl), dtype=np.int64)
        for d in range(1, 4):
            if d <= max(self.hist, 0):
                there = lvl >= d
                state |= np.where(there, (bits >> np.maximum(lvl - d, 0).astype(np.uint64)) & np.uint64(1), np.uint64(0)).astype(np.int64) << (3 - d)
        key, count = np.unique(lvl * 8 + state, return_counts=True)
        return [(int(k) >> 3, int(k) & 7, int(c)) for k, c in zip(key, count)]

    def at_least(self, repair: bool = False) -> np.ndarray:
        """Registers at or above each level, with overflow repaired from the ledger if asked for."""
        now = self.levels()
        up = np.array([np.count_nonzero(now >= t) for t in range(65)], dtype=float)
        if repair:
            for t, x in self.ledger.items():
                if t < 65:
                    up[t] += (self.m - up[t]) * (1 - np.exp(-x / self.m))
        return up

    def repaired_cells(self) -> list[tuple[int, int, float]]:
        up = self.at_least(True)
        return [(t, 0, float(up[t] - up[t + 1])) for t in range(64) if up[t] - up[t + 1] > 0]

    def merge(self, other: FloorSketch) -> FloorSketch:
        """The higher floor is kept; each register is the larger one."""
        self.micro |= other.micro
        self.rows += other.rows
        self.floor = max(self.floor, other.floor)
        self.bits = self._bits() | other._bits()
        for t, x in other.ledger.items():
            self.ledger[t] = self.ledger.get(t, 0) + x
        now = self.levels()
        low = now < self.floor
        if low.any():  # below the floor a register reads as at the floor
            self.bits[low] = np.uint64(1) << np.uint64(max(self.floor, 0))
        high = self.levels() > self.floor + self.top
        if high.any():
            self.bits[high] = np.uint64(1) << np.uint64(self.floor + self.top)
        self._promote()
        return self

    def to_bytes(self) -> bytes:
        """The whole state in a fixed layout: numbers, ledger, bitmaps."""
        head = HEAD.pack(self.m, self.width, self.hist, MODES.index(self.exit_mode), self.lazy, self.floor, self.micro, self.rows, self.passed, self.updates, self.promotions, len(self.ledger), self.bits is not None)
        noted = b"".join(struct.pack("<iq", t, x) for t, x in sorted(self.ledger.items()))
        return head + struct.pack("<q", self.scanned) + noted + (b"" if self.bits is None else self.bits.astype("<u8").tobytes())

    @classmethod
    def from_bytes(cls, raw: bytes) -> FloorSketch:
        m, width, hist, mode, lazy, floor, micro, rows, passed, updates, promotions, noted, full = HEAD.unpack_from(raw)
        at = HEAD.size
        (scanned,) = struct.unpack_from("<q", raw, at)
        ledger = dict(struct.unpack_from("<iq", raw, at + 8 + 12 * i) for i in range(noted))
        at += 8 + 12 * noted
        bits = np.frombuffer(raw, dtype="<u8", count=m, offset=at).astype(np.uint64) if full else None
        return FloorSketch(m, width, hist, MODES[mode], lazy, floor, micro, rows, passed, updates, promotions, scanned, ledger, bits)


@dataclass
class TruncatedOffset:
    """Codes over a shared base, cut off at the top one; no exit test, no history, no ledger.

    The base starts at level 0, where code 0 is an empty register. Once no code is 0 the base rises by the smallest code
    and all codes fall by it, so what was cut off stays below what it was: adding again may change the sketch. The estimate
    is the classic one on the levels that the codes stand for.
    """

    m: int = 2048
    width: int = 4
    base: int = 0
    rows: int = 0
    promotions: int = 0
    codes: np.ndarray | None = None
    updates: int | None = None  # not counted

    @property
    def floor(self) -> int:
        return self.base - 1

    @property
    def passed(self) -> int:
        return self.rows  # there is no exit test

    def add_batch(self, h: np.ndarray, width: int = 64) -> TruncatedOffset:
        if self.codes is None:
            self.codes = np.zeros(self.m, dtype=np.int64)
        h = h.astype(np.uint64, copy=False)
        self.rows += len(h)
        reg, lvl = (h & np.uint64(self.m - 1)).astype(np.int64), levels_of(h, width)
        top = (1 << self.width) - 1
        while len(lvl):
            code = np.minimum(lvl + 1 - self.base, top)
            low = self.codes == self.codes.min()
            rising = np.flatnonzero(low[reg] & (code > self.codes.min()) & (code > 0))
            which, first = np.unique(reg[rising], return_index=True)
            whole = len(which) == int(low.sum())
            upto = int(rising[first].max()) + 1 if whole else len(lvl)  # the base can only rise once the last low one has
            np.maximum.at(self.codes, reg[:upto], np.maximum(code[:upto], 0))
            reg, lvl = reg[upto:], lvl[upto:]
            self._rise()
        return self

    def _rise(self) -> None:
        if (step := int(self.codes.min())) > 0:
            self.base += step
            self.codes = self.codes - step
            self.promotions += step

    def merge(self, other: TruncatedOffset) -> TruncatedOffset:
        """Both at the higher base; each register is the larger one."""
        base, top = max(self.base, other.base), (1 << self.width) - 1
        held = [np.clip(s.levels() + 1 - base, 0, top) for s in (self, other)]
        self.base, self.codes, self.rows = base, np.maximum(*held), self.rows + other.rows
        self._rise()
        return self

    def to_bytes(self) -> bytes:
        return struct.pack("<iiiqq", self.m, self.width, self.base, self.rows, self.promotions) + (self.levels() + 1 - self.base).astype(np.int8).tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> TruncatedOffset:
        m, width, base, rows, promotions = struct.unpack_from("<iiiqq", raw)
        return cls(m, width, base, rows, promotions, np.frombuffer(raw, dtype=np.int8, count=m, offset=struct.calcsize("<iiiqq")).astype(np.int64))

    def levels(self) -> np.ndarray:
        return (self.codes if self.codes is not None else np.zeros(self.m, dtype=np.int64)) + self.base - 1

    def cells(self) -> list[tuple[int, int, int]]:
        now = self.levels()
        lvl, count = np.unique(now[now >= 0], return_counts=True)
        return [(int(a), 0, int(c)) for a, c in zip(lvl, count)]

    def estimate(self) -> float:
        now = self.levels()
        empty = int(np.count_nonzero(now < 0))
        raw = 0.7213 / (1 + 1.079 / self.m) * 2 * self.m * self.m / (float(np.sum(2.0 ** -now[now >= 0].astype(float))) + 2.0 * empty)
        return self.m * float(np.log(self.m / empty)) if empty and raw <= 2.5 * self.m else raw


@dataclass
class TwoBit:
    """Two bits a register: how many steps above a shared threshold a level was seen; the threshold moves up when nearly all are set."""

    m: int = 2048
    step: int = 4
    fill: float = 0.97
    threshold: int = 0
    codes: np.ndarray | None = None

    def add_batch(self, h: np.ndarray, width: int = 64) -> TwoBit:
        if self.codes is None:
            self.codes = np.zeros(self.m, dtype=np.int8)
        reg, lvl = (h & np.uint64(self.m - 1)).astype(np.int64), levels_of(h, width)
        limit = int(self.fill * self.m)
        while len(lvl):
            keep = lvl >= self.threshold
            reg, lvl = reg[keep], lvl[keep]
            room = limit - int(np.count_nonzero(self.codes))
            fresh = np.flatnonzero(self.codes[reg] == 0)
            first = np.sort(fresh[np.unique(reg[fresh], return_index=True)[1]])
            full = len(first) >= max(room, 1)
            upto = int(first[max(room, 1) - 1]) + 1 if full else len(lvl)
            np.maximum.at(self.codes, reg[:upto], np.minimum(1 + (lvl[:upto] - self.threshold) // self.step, 3).astype(np.int8))
            reg, lvl = reg[upto:], lvl[upto:]
            while np.count_nonzero(self.codes) >= limit:
                self.threshold += self.step
                self.codes = np.maximum(self.codes - 1, 0).astype(np.int8)
        return self

    def estimate(self) -> float:
        zeros = self.m if self.codes is None else int(np.count_nonzero(self.codes == 0))
        return 2.0**self.threshold * self.m * float(np.log(self.m / max(zeros, 0.5)))


def sequential(df: DataFrame, cols: Sequence[str | Column], make, by: Sequence[str] = (), kind: str = "xxhash64", width: int = 64) -> DataFrame:
    """Rows (by..., part, rows, floor, promotions, passed, updates, cells, sketch): one FloorSketch for each group a partition meets.

    make: a function that returns a new sketch. Sketches of one group from several partitions are merged by merge_sketches();
    each holds a few kilobytes, whatever it has seen, and a task holds one at a time: its rows are sorted by group first.
    """
    rows = hashed(df, cols, by, kind)
    rows = rows.sortWithinPartitions(*by) if by else rows
    names = list(by)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields if f.name != "h"), "part int, rows long, floor int, promotions long, passed long, updates long, cells array<struct<lvl: int, state: int, cnt: bigint>>, sketch binary"])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()

        def told(key: tuple, s: FloorSketch) -> pd.DataFrame:
            cells = [{"lvl": a, "state": b, "cnt": c} for a, b, c in s.cells()]
            return pd.DataFrame([dict(zip(names, key)) | {"part": part, "rows": s.rows, "floor": s.floor, "promotions": s.promotions, "passed": s.passed, "updates": s.updates, "cells": cells, "sketch": s.to_bytes()}])

        same = lambda a, b: all(x == y or (pd.isna(x) and pd.isna(y)) for x, y in zip(a, b))
        open_key, sketch = None, None
        for pdf in batches:
            groups = pdf.groupby(names, dropna=False, sort=False)["h"] if names else [((), pdf["h"])]
            for key, h in groups:
                key = key if isinstance(key, tuple) else (key,)
                if sketch is not None and not same(key, open_key):
                    yield told(open_key, sketch)
                    sketch = None
                open_key, sketch = key, (sketch or make()).add_batch(h.to_numpy().astype(np.int64).view(np.uint64), width)
        if sketch is not None:
            yield told(open_key, sketch)

    return rows.mapInPandas(run, schema)


def merge_sketches(parts: DataFrame, by: Sequence[str] = (), kind: type = FloorSketch) -> DataFrame:
    """Rows (by..., rows, floor, cells): each group's sketches merged one after the other by part; kind: their type."""
    names = list(by)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in parts.schema.fields if f.name in names), "rows long, floor int, cells array<struct<lvl: int, state: int, cnt: bigint>>"])

    def run(key: tuple[Any, ...], batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        whole = None
        for pdf in batches:
            for raw in pdf.sort_values("part")["sketch"]:
                s = kind.from_bytes(bytes(raw))
                whole = s if whole is None else whole.merge(s)
        yield pd.DataFrame([dict(zip(names, key)) | {"rows": whole.rows, "floor": whole.floor, "cells": [{"lvl": a, "state": b, "cnt": c} for a, b, c in whole.cells()]}])

    return parts.groupBy(*names).applyInPandas(run, schema)
