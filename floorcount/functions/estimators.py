"""Every estimate as an expression over one register summary.

`cells` is an array of (lvl, state, cnt): how many registers have this largest level and this history. Its size is bounded
by the number of levels and states, whatever was counted, so all estimates of a group are one projection.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from floorcount.functions import constants as K

TOP = 63
HISTORY = 3


def _table(values) -> Column:
    """Fixed numbers as one constant array: a text that the optimizer reads once, instead of an expression a number."""
    return F.split(F.lit(",".join(map(repr, map(float, values)))), ",").cast("array<double>")


def _sum(cells: Column, term) -> Column:
    return F.aggregate(cells, F.lit(0.0), lambda s, x: s + term(x))


def _count(cells: Column, keep=None) -> Column:
    one = (lambda x: x["cnt"]) if keep is None else (lambda x: F.when(keep(x), x["cnt"]).otherwise(F.lit(0).cast("bigint")))
    return F.aggregate(cells, F.lit(0).cast("bigint"), lambda s, x: s + one(x))


def filled(cells: Column) -> Column:
    return _count(cells)


def below(cells: Column, m: int, t) -> Column:
    """Registers below level t, empty ones among them."""
    return F.lit(m) - _count(cells, lambda x: x["lvl"] >= t)


def floor_level(cells: Column, m: int) -> Column:
    """-1 while a register is empty, else the smallest level."""
    return F.when(filled(cells) < m, F.lit(-1)).otherwise(F.array_min(F.transform(cells, lambda x: x["lvl"]))).cast("int")


def state_of(state: Column, h: int) -> Column:
    """The h bits next to the top of a state of HISTORY bits."""
    return F.shiftright(state, HISTORY - h)


def est_lc(cells: Column, m: int) -> Column:
    """Linear counting; where no register is empty, as if half a one were."""
    return m * F.ln(F.lit(float(m)) / F.greatest(below(cells, m, 0).cast("double"), F.lit(0.5)))


def est_tlc_at(cells: Column, m: int, t) -> Column:
    """Linear counting with registers below level t taken as empty; null where there are none of them, or only them."""
    z = below(cells, m, t)
    t = F.lit(t) if isinstance(t, int) else t
    return F.when((z > 0) & (z < m), F.pow(F.lit(2.0), t) * m * F.ln(F.lit(float(m)) / F.when(z > 0, z)))


def est_lc_floor(cells: Column, m: int) -> Column:
    t = floor_level(cells, m) + 1
    z = below(cells, m, t)
    return F.pow(F.lit(2.0), t) * m * F.ln(F.lit(float(m)) / F.greatest(z.cast("double"), F.lit(0.5)))


def tiers(cells: Column, m: int, top: int = TOP) -> Column:
    """Array of (t, z), for tiers with some register below and some not: from the lowest that can have one to the largest level."""
    first = F.greatest(floor_level(cells, m) + 1, F.lit(0))
    last = F.least(F.array_max(F.transform(cells, lambda x: x["lvl"])), F.lit(top))
    none = F.array().cast("array<int>")
    at = F.coalesce(F.when(last >= first, F.sequence(first, last)), none)
    return F.filter(F.transform(at, lambda t: F.struct(t.alias("t"), below(cells, m, t).alias("z"))), lambda x: (x["z"] > 0) & (x["z"] < m))


def est_tlc_best(cells: Column, m: int, target: float = 0.25) -> Column:
    """The tier whose count below is nearest target * m; two at one distance are averaged."""
    far = F.transform(tiers(cells, m), lambda x: F.struct(F.abs(x["z"] - F.lit(target * m)).alias("far"), x["t"].alias("t"), x["z"].alias("z")))
    near = F.array_min(F.transform(far, lambda x: x["far"]))
    best = F.filter(far, lambda x: x["far"] == near)
    return F.when(F.size(best) > 0, F.aggregate(best, F.lit(0.0), lambda s, x: s + F.pow(F.lit(2.0), x["t"]) * m * F.ln(m / x["z"])) / F.size(best))


def est_tlc(cells: Column, m: int, p: float = 4.5, guard: bool = True) -> Column:
    """The tiers' counts blended in log space, by their expected errors to the power -p.

    guard: with 30 to 40 per cent of registers empty it passes over to linear counting at the floor.
    """

    def weigh(s, x):
        log = F.ln(m / x["z"])
        error = math.sqrt(2 / math.pi) * F.sqrt((m - x["z"]) / (F.lit(float(m)) * x["z"])) / log
        w = F.pow(error, F.lit(-p))
        return F.struct((s["w"] + w).alias("w"), (s["e"] + w * (x["t"] * math.log(2) + F.ln(m * log))).alias("e"))

    blend = F.aggregate(tiers(cells, m), F.struct(F.lit(0.0).alias("w"), F.lit(0.0).alias("e")), weigh, lambda s: F.when(s["w"] > 0, F.exp(s["e"] / F.when(s["w"] > 0, s["w"]))))
    if not guard:
        return blend
    ramp = F.least(F.greatest((below(cells, m, 0) / F.lit(float(m)) - 0.3) / 0.1, F.lit(0.0)), F.lit(1.0))
    low = est_lc_floor(cells, m)
    return F.when(ramp <= 0, blend).when((ramp >= 1) | blend.isNull(), low).otherwise(ramp * low + (1 - ramp) * blend)


def harmonic_sum(cells: Column, h: int = 0) -> Column:
    """Sum of 2^-level over filled registers; with h, levels shifted by what the history says."""
    if not h:
        return _sum(cells, lambda x: x["cnt"] * F.pow(F.lit(2.0), -x["lvl"]))
    return _sum(cells, lambda x: x["cnt"] * F.pow(F.lit(2.0), -(x["lvl"] + _shift(x, h))))


def _shift(x: Column, h: int) -> Column:
    """A register at level r < h has r observable bits, and that many bits' corrections."""
    out = F.get(_table(K.level_shifts(h)), state_of(x["state"], h))
    for r in range(h - 1, -1, -1):
        some = F.get(_table(K.level_shifts(r)), state_of(x["state"], r)) if r else F.lit(0.0)
        out = F.when(x["lvl"] == r, some).otherwise(out)
    return out


def est_occ_mean(cells: Column, m: int, h: int = 0) -> Column:
    """The harmonic mean with a coefficient that follows the share of filled registers; raw, see corrected()."""
    c, s = filled(cells), harmonic_sum(cells, h)
    return F.when(c > 0, (c + m) / F.lit(2.0 * m) * 2 * c * c / F.when(c > 0, s)).otherwise(0.0)


def alpha(m: int) -> float:
    return 0.7213 / (1 + 1.079 / m)


def est_harm_mean(cells: Column, m: int) -> Column:
    c, s = filled(cells), harmonic_sum(cells)
    return F.when(c > 0, F.lit(alpha(m)) * 2 * c * c / F.when(c > 0, s)).otherwise(0.0)


def est_geo_mean(cells: Column, m: int) -> Column:
    c = filled(cells)
    mean = _sum(cells, lambda x: x["cnt"] * x["lvl"]) / F.when(c > 0, c)
    return F.when(c > 0, 2 * F.pow(F.lit(2.0), mean) * (c + m) / F.lit(2.0 * m)).otherwise(0.0)


def est_hll(cells: Column, m: int, threshold: float = 2.5) -> Column:
    """The classic two regimes: linear counting below threshold * m while a register is empty, else the harmonic mean of all."""
    empty = F.lit(m) - filled(cells)
    raw = F.lit(alpha(m)) * 2 * m * m / (harmonic_sum(cells) + 2.0 * empty)
    return F.when((empty > 0) & (raw <= threshold * m), est_lc(cells, m)).otherwise(raw)


def fold(value: Column, largest: float) -> tuple[Column, Column]:
    """(value halved until it is at most largest, the number of halvings), without a loop."""
    k = F.greatest(F.ceil(F.log2(value / F.lit(largest))), F.lit(0))
    return value / F.pow(F.lit(2.0), k), k


def corrected(raw: Column, m: int, method: str = "occ_mean", h: int = 0) -> Column:
    """raw by one look at the table of expected raw values; beyond the table's end by octaves, below its start in proportion."""
    first, knots = K.correction_knots(method, m, h)
    last = first + K.STEP * (K.KNOTS - 2)
    inside, k = fold(raw, math.exp(last))
    at = F.greatest((F.ln(inside) - F.lit(first)) / F.lit(K.STEP), F.lit(0.0))
    low = F.least(F.floor(at).cast("int"), F.lit(K.KNOTS - 2))
    table = _table(knots)
    a, b = F.get(table, low), F.get(table, low + 1)
    start = math.exp(first)
    return F.when(raw <= 0, 0.0).when(raw < start, raw * math.exp(knots[0]) / start).otherwise(F.exp(a + (b - a) * (at - low)) * F.pow(F.lit(2.0), k))


def est_mean_hist(cells: Column, m: int, h: int) -> Column:
    return corrected(est_occ_mean(cells, m, h), m, "occ_mean", h)


def est_hybrid(cells: Column, m: int, h: int = 0, lo: float = 0.2, hi: float = 5.0) -> Column:
    """Linear counting at the floor below lo * m, the corrected mean from hi * m, between them a mix by the logarithm."""
    lc, mean = est_lc_floor(cells, m), est_mean_hist(cells, m, h)
    w = F.ln(F.greatest(lc, F.lit(lo * m)) / F.lit(lo * m)) / F.lit(math.log(hi / lo))
    return F.when(lc <= lo * m, lc).when(lc >= hi * m, mean).otherwise((1 - w) * lc + w * mean)


def est_hist_lc(cells: Column, m: int, h: int = 2, least: int = 8) -> Column:
    """Linear counting from history bits alone: of registers that can tell of a level, those that never saw it."""

    def at(i):
        able = _count(cells, lambda x: (x["lvl"] > i) & (x["lvl"] <= i + h))
        seen = _count(cells, lambda x: (x["lvl"] > i) & (x["lvl"] <= i + h) & (F.call_function("shiftright", x["state"], (F.lit(HISTORY) - (x["lvl"] - i)).cast("int")).bitwiseAND(F.lit(1)) == 1))
        return F.struct(i.alias("i"), able.alias("n"), (able - seen).alias("u"))

    # a level that history can tell of is under the largest one, and at most h under the smallest
    low, high = F.array_min(F.transform(cells, lambda x: x["lvl"])), F.array_max(F.transform(cells, lambda x: x["lvl"]))
    span = F.coalesce(F.when(high >= 1, F.sequence(F.greatest(low - h, F.lit(0)), high - 1)), F.array().cast("array<int>"))
    levels = F.filter(F.transform(span, at), lambda x: (x["n"] >= least) & (x["u"] > 0) & (x["u"] < x["n"]))

    def weigh(s, x):
        log = F.ln(x["n"] / x["u"])
        w = F.pow(log, F.lit(2.0)) * x["n"] * x["u"] / (x["n"] - x["u"])
        return F.struct((s["w"] + w).alias("w"), (s["e"] + w * ((x["i"] + 1) * math.log(2) + F.ln(m * log))).alias("e"))

    return F.aggregate(levels, F.struct(F.lit(0.0).alias("w"), F.lit(0.0).alias("e")), weigh, lambda s: F.when(s["w"] > 0, F.exp(s["e"] / F.when(s["w"] > 0, s["w"]))))


def est_tlc_layered(cells: Column, m: int, h: int = 2, w: float = 0.5) -> Column:
    """Tiers and history in equal parts; below 3 * m, where history tells little, tiers alone."""
    tlc, hist = est_tlc(cells, m), est_hist_lc(cells, m, h)
    return F.when(hist.isNull() | (tlc < 3 * m), tlc).otherwise(w * tlc + (1 - w) * hist)


def est_hybrid_layered(cells: Column, m: int, w: float = 0.5) -> Column:
    return w * est_tlc_layered(cells, m) + (1 - w) * est_hybrid(cells, m, 2)


def est_gra(cells: Column, m: int, h: int = 2) -> Column:
    """The closed-form remaining-area estimate.

    Empty registers, and history below level 0, are what a sketch with levels below 0 would hold: each contributes what it is
    expected to under linear counting's rate.
    """
    tau, k, g = K.remaining_area(h)
    weights = _table(g)
    rate = est_lc(cells, m) / m
    held = _sum(cells, lambda x: x["cnt"] * F.pow(F.lit(2.0), F.lit(-tau) * (x["lvl"] + 1)) * _known(x, h, weights, g, rate))
    empty = F.lit(m) - filled(cells)
    virtual = F.lit(0.0)
    for r in range(-1, -13, -1):
        # every level from r + 1 to -1 unseen, r seen: rates double at each step down
        above = 2.0 ** (-r) - 2
        x = rate * 2.0 ** -(r + 1)
        virtual = virtual + F.exp(-rate * (above / 2)) * (1 - F.exp(-x)) * 2.0 ** (-tau * (r + 1)) * _expected(h, g, x, 1, 0)
    z = held + F.when(empty > 0, empty * virtual).otherwise(0.0)
    return F.when(filled(cells) > 0, m * F.pow(F.lit(m * k) / F.when(z > 0, z), F.lit(1 / tau))).otherwise(0.0)


def _expected(h: int, g: tuple[float, ...], x: Column, first: int, known: int) -> Column:
    """Mean of g over the bits from `first` on, at a level's rate x; the bits before are those of `known`."""
    out = F.lit(0.0)
    rest = h - first + 1
    for bits in range(1 << rest):
        p = F.lit(1.0)
        for d in range(first, h + 1):
            unseen = F.exp(-x * 2.0**d)
            p = p * ((1 - unseen) if bits >> (h - d) & 1 else unseen)
        out = out + p * g[(known << rest) | bits]
    return out


def _known(x: Column, h: int, weights: Column, g: tuple[float, ...], rate: Column) -> Column:
    out = F.get(weights, state_of(x["state"], h))
    for r in range(h - 1, -1, -1):
        here = rate * 2.0 ** -(r + 1)
        some = F.array(*[_expected(h, g, here, r + 1, s) for s in range(1 << r)])
        out = F.when(x["lvl"] == r, F.get(some, state_of(x["state"], r) if r else F.lit(0))).otherwise(out)
    return out


def est_mle(cells: Column, m: int, h: int = 2, steps: int = 12) -> Column:
    """Most likely n given levels and h history bits, by Newton's method on log n."""
    empty = F.lit(m) - filled(cells)

    def both(lam: Column, x: Column) -> tuple[Column, Column]:
        """Derivative of the log-likelihood by log n, and its derivative, for a register."""
        rate = lam * F.pow(F.lit(2.0), -(x["lvl"] + 1))
        v = F.greatest(rate, F.lit(1e-12))
        grow = lambda y: y / F.expm1(y)
        steep = lambda y: grow(y) * (1 - y - grow(y))
        f, d = grow(v) - v, steep(v) - v
        for k in range(1, h + 1):
            y = v * 2.0**k
            y = F.least(y, F.lit(600.0))
            seen = F.shiftright(x["state"], HISTORY - k).bitwiseAND(F.lit(1)) == 1
            there = x["lvl"] >= k
            f = f + F.when(~there, 0.0).when(seen, grow(y)).otherwise(-y)
            d = d + F.when(~there, 0.0).when(seen, steep(y)).otherwise(-y)
        return x["cnt"] * f, x["cnt"] * d

    def step(u: Column, _: Column) -> Column:
        lam = F.exp(u)
        total = F.aggregate(cells, F.struct((-lam * empty).alias("f"), (-lam * empty).alias("d")), lambda s, x: F.struct((s["f"] + both(lam, x)[0]).alias("f"), (s["d"] + both(lam, x)[1]).alias("d")))
        move = F.when(total["d"] < 0, -total["f"] / total["d"]).otherwise(0.0)
        return u + F.least(F.greatest(move, F.lit(-1.0)), F.lit(1.0))

    start = F.ln(F.greatest(est_occ_mean(cells, m) / F.lit(1.4 * m), F.lit(1e-9)))
    return F.when(filled(cells) > 0, m * F.exp(F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step))).otherwise(0.0)


def est_micro(micro: Column) -> Column:
    """Linear counting over a bitmap of 64."""
    return 64.0 * F.ln(F.lit(64.0) / F.greatest(F.lit(64) - F.bit_count(micro), F.lit(0.5)))


def set_history(cells: Column, h: int) -> Column:
    """History bits that are set in all registers."""
    return F.aggregate(cells, F.lit(0).cast("bigint"), lambda s, x: s + x["cnt"] * F.bit_count(state_of(x["state"], h).cast("bigint")))


def est_lc_with_floors(cells: Column, m: int, micro: Column, h: int = 0) -> Column:
    """Linear counting, at least what the small bitmap and the registers with their history have seen."""
    seen = filled(cells) + (set_history(cells, h) if h else F.lit(0))
    return F.greatest(est_lc(cells, m), F.bit_count(micro).cast("double"), seen.cast("double"))


def est_loglog(cells: Column, m: int, keep: float = 1.0) -> Column:
    """m times two to the mean level, over the smallest `keep` of the registers; raw. Empty registers count as level -1."""
    n = int(m * keep)
    ordered = F.concat(F.array(F.struct(F.lit(-1).alias("lvl"), (F.lit(m) - filled(cells)).alias("cnt"))), F.transform(F.array_sort(cells), lambda x: F.struct(x["lvl"].alias("lvl"), x["cnt"].alias("cnt"))))
    total = F.aggregate(ordered, F.struct(F.lit(0).cast("bigint").alias("k"), F.lit(0.0).alias("s")), lambda s, x: F.struct((s["k"] + x["cnt"]).alias("k"), (s["s"] + F.greatest(F.least(x["cnt"], n - s["k"]), F.lit(0)) * (x["lvl"] + 1)).alias("s")), lambda s: s["s"])
    return m * F.pow(F.lit(2.0), total / n)


ESTIMATORS = {
    "lc": est_lc, "lc_floor": est_lc_floor, "tlc_best": est_tlc_best, "tlc": est_tlc, "occ_mean": est_occ_mean, "harm_mean": est_harm_mean, "geo_mean": est_geo_mean,
    "hll": est_hll, "hybrid": est_hybrid, "mean_h1": lambda c, m: est_mean_hist(c, m, 1), "mean_h2": lambda c, m: est_mean_hist(c, m, 2), "mean_h3": lambda c, m: est_mean_hist(c, m, 3),
    "hybrid_h2": lambda c, m: est_hybrid(c, m, 2), "hist_lc": est_hist_lc, "tlc_layered": est_tlc_layered, "tlc_layered_h1": lambda c, m: est_tlc_layered(c, m, 1), "tlc_layered_h3": lambda c, m: est_tlc_layered(c, m, 3), "hybrid_layered": est_hybrid_layered, "gra": est_gra, "mle": est_mle,
    "loglog": est_loglog, "loglog_trunc": lambda c, m: est_loglog(c, m, 0.7),
}
