"""DuckDB SQL for the queries' results: relational, over one row a register, where the engine's plans fold arrays."""

from __future__ import annotations

import math

from floorcount.functions import constants as K

KEYS = ("l_orderkey", "l_partkey", "l_suppkey")
STACKED = " UNION ALL ".join(f"SELECT '{k}' AS g, {k}::VARCHAR AS e FROM lineitem" for k in KEYS)


def base(source: str = STACKED, m: int = 2048, mod: bool = False, floors: bool = True) -> str:
    """CTEs: h (hashes), r (bitmaps), s (level and state), z (below each tier), k (one row a group), b (with the floor's count).

    source: SELECT g, e, with e as text.
    """
    reg = f"h % {m}" if not mod else f"(h & 4294967295) % {m}"
    k = max(1, (m - 1).bit_length())
    return f"""WITH RECURSIVE e AS ({source}),
h AS (SELECT g, cast('0x' || substr(md5(e), 1, 15) AS BIGINT) AS h FROM e WHERE e IS NOT NULL),
l AS (SELECT g, ({reg})::INT AS reg, (60 - CASE WHEN h = 0 THEN 0 ELSE length(bin(h)) END)::INT AS lvl, ((h >> {k}) & 63)::INT AS place FROM h),
r AS (SELECT g, reg, bit_or(1::BIGINT << lvl) AS bits, max(lvl) AS lvl FROM l GROUP BY ALL),
s AS (SELECT *, ((CASE WHEN lvl >= 3 THEN bits >> (lvl - 3) ELSE bits << (3 - lvl) END) & 7)::INT AS state FROM r),
z AS (SELECT g, t, {m} - count(*) FILTER (WHERE lvl >= t) AS z FROM s, (SELECT unnest(generate_series(0, 63))::INT AS t) GROUP BY ALL),
k AS (SELECT g, count(*) AS c, {m} - count(*) AS z0, sum(pow(2.0, -lvl)) AS s, avg(lvl) AS mean, CASE WHEN count(*) < {m} THEN -1 ELSE min(lvl) END::INT AS f FROM s GROUP BY g)""" + (f""",
b AS (SELECT k.*, {m} * ln({m} / greatest(z0, 0.5)) AS lc, pow(2.0, f + 1) * {m} * ln({m} / greatest(z.z, 0.5)) AS lcf FROM k JOIN z ON z.g IS NOT DISTINCT FROM k.g AND z.t = k.f + 1)""" if floors else "")


def tlc(m: int = 2048, guard: bool = True) -> str:
    """CTE t (g, tlc)."""
    blend = f"""w AS (SELECT g, exp(sum(w * le) / sum(w)) AS blend FROM (SELECT g, pow(sqrt(2 / pi()) * sqrt(({m} - z) / ({m}.0 * z)) / ln({m}.0 / z), -4.5) AS w, t * ln(2) + ln({m} * ln({m}.0 / z)) AS le FROM z WHERE z > 0 AND z < {m}) GROUP BY g)"""
    if not guard:
        return f"{blend}, t AS (SELECT g, blend AS tlc FROM w)"
    return f"""{blend},
t AS (SELECT b.g, CASE WHEN ramp <= 0 THEN blend WHEN ramp >= 1 OR blend IS NULL THEN lcf ELSE ramp * lcf + (1 - ramp) * blend END AS tlc
  FROM (SELECT *, least(greatest((z0 / {m}.0 - 0.3) / 0.1, 0), 1) AS ramp FROM b) b LEFT JOIN w ON w.g IS NOT DISTINCT FROM b.g)"""


def shift(h: int) -> str:
    def of(bits: int) -> str:
        return f"[{', '.join(repr(v) for v in K.level_shifts(bits))}][(state >> {3 - bits}) + 1]" if bits else "0.0"

    cases = " ".join(f"WHEN lvl = {r} THEN {of(r)}" for r in range(h))
    return f"CASE {cases} ELSE {of(h)} END" if h else "0.0"


def corrected(raw: str, m: int = 2048, method: str = "occ_mean", h: int = 0) -> str:
    first, knots = K.correction_knots(method, m, h)
    last = math.exp(first + K.STEP * (K.KNOTS - 2))
    k = f"greatest(ceil(log2({raw} / {last!r})), 0)"
    inside = f"({raw} / pow(2.0, {k}))"
    at = f"greatest((ln({inside}) - {first!r}) / {K.STEP!r}, 0)"
    low = f"least(floor({at}), {K.KNOTS - 2})::INT"
    table = f"(SELECT [{', '.join(repr(v) for v in knots)}])"
    a, b = f"{table}[{low} + 1]", f"{table}[{low} + 2]"
    start = math.exp(first)
    return f"CASE WHEN {raw} <= 0 THEN 0 WHEN {raw} < {start!r} THEN {raw} * {math.exp(knots[0]) / start!r} ELSE exp({a} + ({b} - {a}) * ({at} - {low})) * pow(2.0, {k}) END"


def mean_h(h: int, m: int = 2048) -> str:
    """CTE m{h} (g, raw, mean)."""
    raw = f"m{h}_ AS (SELECT g, (count(*) + {m}) / ({m} * 2.0) * 2 * count(*) * count(*) / sum(pow(2.0, -(lvl + {shift(h)}))) AS raw FROM s GROUP BY g)"
    return f"{raw}, m{h} AS (SELECT g, raw, {corrected('raw', m, 'occ_mean', h)} AS mean FROM m{h}_)"


def hybrid(h: int, m: int = 2048) -> str:
    """CTE y{h} (g, hybrid); needs mean_h(h)."""
    w = f"(ln(greatest(lcf, 0.2 * {m}) / (0.2 * {m})) / ln(25.0))"
    return f"y{h} AS (SELECT b.g, CASE WHEN lcf <= 0.2 * {m} THEN lcf WHEN lcf >= 5.0 * {m} THEN m{h}.mean ELSE (1 - {w}) * lcf + {w} * m{h}.mean END AS hybrid FROM b JOIN m{h} ON b.g IS NOT DISTINCT FROM m{h}.g)"


def hist_lc(h: int = 2, m: int = 2048) -> str:
    """CTE hl (g, hist_lc), null where history says nothing."""
    return f"""hl_ AS (SELECT g, i, count(*) AS n, count(*) FILTER (WHERE ((state >> (3 - (lvl - i))) & 1) = 0) AS u FROM s, (SELECT unnest(generate_series(0, 62))::INT AS i) WHERE lvl > i AND lvl <= i + {h} GROUP BY ALL),
hw AS (SELECT g, exp(sum(w * le) / sum(w)) AS hist_lc FROM (SELECT g, pow(ln(n / u::DOUBLE), 2) * n * u / (n - u) AS w, (i + 1) * ln(2) + ln({m} * ln(n / u::DOUBLE)) AS le FROM hl_ WHERE n >= 8 AND u > 0 AND u < n) GROUP BY g),
hl AS (SELECT k.g, hist_lc FROM k LEFT JOIN hw ON hw.g IS NOT DISTINCT FROM k.g)"""


def layered(m: int = 2048) -> str:
    """CTE ly (g, tlc_layered); needs tlc() and hist_lc()."""
    return f"ly AS (SELECT t.g, CASE WHEN hist_lc IS NULL OR tlc < 3 * {m} THEN tlc ELSE 0.5 * tlc + 0.5 * hist_lc END AS tlc_layered FROM t JOIN hl ON t.g IS NOT DISTINCT FROM hl.g)"


def gra(h: int = 2, m: int = 2048) -> str:
    """CTE ga (g, gra)."""
    tau, k, g = K.remaining_area(h)

    def expected(x: str, first: int, known: int) -> str:
        rest = h - first + 1
        terms = []
        for bits in range(1 << rest):
            p = [f"(1 - exp(-{x} * {2.0**d}))" if bits >> (h - d) & 1 else f"exp(-{x} * {2.0**d})" for d in range(first, h + 1)]
            terms.append(" * ".join([*p, repr(g[(known << rest) | bits])]))
        return "(" + " + ".join(terms) + ")"

    virtual = " + ".join(f"exp(-rate * {(2.0 ** (-r) - 2) / 2}) * (1 - exp(-(rate * {2.0 ** -(r + 1)}))) * {2.0 ** (-tau * (r + 1))!r} * {expected(f'(rate * {2.0 ** -(r + 1)})', 1, 0)}" for r in range(-1, -13, -1))
    known = " ".join(f"WHEN lvl = {r} AND (state >> {3 - r}) = {s} THEN {expected(f'(rate * {2.0 ** -(r + 1)})', r + 1, s)}" for r in range(h) for s in range(1 << r))
    each = f"pow(2.0, {-tau!r} * (lvl + 1)) * (CASE {known} ELSE [{', '.join(map(repr, g))}][(state >> {3 - h}) + 1] END)"
    return f"""ga_ AS (SELECT b.g, any_value(z0) AS z0, any_value(rate) AS rate, sum({each}) AS held FROM s JOIN (SELECT *, lc / {m} AS rate FROM b) b ON s.g IS NOT DISTINCT FROM b.g GROUP BY b.g),
ga AS (SELECT g, {m} * pow({m * k!r} / (held + CASE WHEN z0 > 0 THEN z0 * ({virtual}) ELSE 0 END), {1 / tau!r}) AS gra FROM ga_)"""


def chain(*parts: str) -> str:
    return ",\n".join(parts)


def estimate(name: str, column: str, table: str, *ctes: str, source: str = STACKED, m: int = 2048) -> str:
    return f"{chain(base(source, m), *ctes)} SELECT g, round({column}, 4) AS {name} FROM {table}"
