"""Numbers that the estimators need, from closed forms rather than from simulation.

A register's level i is unseen with probability exp(-x), x = n / (m * 2^(i+1)), independently of other levels. So for a
register whose largest level has rate x, probabilities of its history are sums of exponentials in x, and the moments over
a linear or a logarithmic sweep of n are rational or Gamma functions.
"""

from __future__ import annotations

import math
from functools import cache

import numpy as np

STEP = math.log(1.01)
#: Cells of the octave-folded correction table, in steps of one per cent of the raw estimate.
KNOTS = 1605


@cache
def state_terms(h: int, state: int) -> tuple[tuple[float, float], ...]:
    """(coefficient, exponent) of sum c * exp(-k x): the chance of a maximum with this history, bits from the top."""
    terms = {1.0: 1.0, 2.0: -1.0}
    for d in range(1, h + 1):
        seen = state >> (h - d) & 1
        made: dict[float, float] = {}
        for k, c in terms.items():
            for shift, factor in (((0.0, 1.0), (2.0**d, -1.0)) if seen else ((2.0**d, 1.0),)):
                made[k + shift] = made.get(k + shift, 0.0) + c * factor
        terms = made
    return tuple((c, k) for k, c in terms.items() if c)


def _moment(terms: tuple[tuple[float, float], ...], power: float) -> float:
    """Integral of x^(power - 1) times the sum, over x from 0."""
    return sum(c * math.gamma(power) * k**-power for c, k in terms)


@cache
def level_shifts(h: int) -> tuple[float, ...]:
    """Additive correction of the level for each history state, under a linear sweep of n; 0 where h is 0."""
    base = state_terms(0, 0)
    mean = _moment(base, 2) / _moment(base, 1)
    return tuple(math.log2(_moment(t, 2) / _moment(t, 1) / mean) for t in (state_terms(h, s) for s in range(1 << h)))


@cache
def remaining_area(h: int) -> tuple[float, float, tuple[float, ...]]:
    """(tau, K, g by state) of the closed-form remaining-area estimator with the least variance."""

    def at(tau: float) -> tuple[float, float, list[float]]:
        b = [_moment(state_terms(h, s), tau) for s in range(1 << h)]
        a = [_moment(state_terms(h, s), 2 * tau) for s in range(1 << h)]
        gain = sum(x * x / y for x, y in zip(b, a))
        g = [x / y for x, y in zip(b, a)]
        return (math.log(2) / gain - 1) / tau**2, sum(x * y for x, y in zip(g, b)) / math.log(2), g

    low, high = 0.3, 1.6
    for _ in range(80):  # the variance has one minimum in tau
        p, q = low + (high - low) / 3, high - (high - low) / 3
        low, high = (low, q) if at(p)[0] < at(q)[0] else (p, high)
    tau = (low + high) / 2
    _, k, g = at(tau)
    return tau, k, tuple(g)


def variance_factor(h: int) -> float:
    """m times the relative variance that the remaining-area estimator reaches."""
    tau, k, g = remaining_area(h)
    b = [_moment(state_terms(h, s), tau) for s in range(1 << h)]
    a = [_moment(state_terms(h, s), 2 * tau) for s in range(1 << h)]
    return (math.log(2) / sum(x * x / y for x, y in zip(b, a)) - 1) / tau**2


def expected_raw(method: str, n: np.ndarray, m: int, h: int = 0) -> np.ndarray:
    """The raw estimate at the expected register state, for n distinct elements."""
    lam = np.asarray(n, dtype=float) / m
    filled = m * -np.expm1(-lam)
    total, mean = np.zeros_like(lam), np.zeros_like(lam)
    for i in range(0, 64):
        x = lam * 2.0 ** -(i + 1)
        top = np.exp(-x) * -np.expm1(-x)
        if method == "geo_mean":
            mean += m * top * i
        bits = min(h, i)
        shifts = level_shifts(bits)
        for s in range(1 << bits):
            p = top.copy()
            for d in range(1, bits + 1):
                unseen = np.exp(-x * 2.0**d)
                p *= (1 - unseen) if s >> (bits - d) & 1 else unseen
            total += m * p * 2.0 ** -(i + shifts[s])
    with np.errstate(divide="ignore", invalid="ignore"):
        occupancy = (filled + m) / (2 * m)
        if method == "geo_mean":
            return 2 * 2 ** (mean / filled) * occupancy
        if method == "harm_mean":
            return 0.7213 / (1 + 1.079 / m) * 2 * filled**2 / total
        return occupancy * 2 * filled**2 / total


@cache
def correction_knots(method: str, m: int, h: int = 0) -> tuple[float, tuple[float, ...]]:
    """(logarithm of the first raw value, logarithm of n at KNOTS raw values in steps of one per cent).

    Keyed by the expected raw estimate, which rises with n, so one lookup corrects without iterating.
    """
    n = np.exp(np.linspace(math.log(m * 1e-4), math.log(m * 2.0**14), 12_000))
    raw = np.log(np.maximum.accumulate(expected_raw(method, n, m, h)))
    first = float(math.log(m) - 3.0)
    grid = first + STEP * np.arange(KNOTS)
    rising = np.concatenate([[True], np.diff(raw) > 0])
    return first, tuple(float(v) for v in np.interp(grid, raw[rising], np.log(n)[rising]))


def ghost_overflow(m: int) -> float:
    """Clamped values that a tier of three-bit registers collects in an era."""
    return m * math.log(2 * m) / 256


def promotion_at(t: int, m: int) -> float:
    """Distinct elements at about which the floor reaches level t."""
    return m * 2.0**t * math.log(m)


def overflow_probability(width: int) -> float:
    """Chance that an update that passes the floor exceeds an offset of `width` bits."""
    return 2.0 ** -(2**width)


def standard_error(m: int) -> float:
    return 1.04 / math.sqrt(m)
