"""Queries of the sketches, their estimators, baselines, measures and workloads, with SQL for what SQL can express.

Those with SQL use a hash that other engines have too; everything else takes the faster one.
"""

from __future__ import annotations

import tempfile
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from floorcount.functions import constants as K
from floorcount.functions import estimators as E
from floorcount.functions import hashing as H
from floorcount.operators import encode, levels, sets, shingles, state, udf
from floorcount.plans import measures, oracles, simulate
from floorcount.sources import store
from floorcount.sources.tables import load_table

M, SQL_HASH = 2048, "md5_60"
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def note(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return note


def add(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    f.__name__ = name
    query(sql)(f)


def stacked(spark: SparkSession, d: str) -> DataFrame:
    """Rows (g, e) of three keys of lineitem: one scan, one sketch a key; they stand for few, about as many, and many elements a register."""
    each = F.array(*[F.struct(F.lit(k).alias("g"), F.col(k).alias("e")) for k in oracles.KEYS])
    return load_table(spark, d, "lineitem", oracles.KEYS).select(F.explode(each).alias("x")).select("x.g", "x.e")


def bitmaps(spark: SparkSession, d: str, m: int = M, addressing: str = "mask") -> DataFrame:
    return levels.build_levels(stacked(spark, d), ["e"], ["g"], m, SQL_HASH, addressing)


def order_keys(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "orders", ["o_orderkey"])


def summaries(spark: SparkSession, d: str) -> DataFrame:
    return levels.summarize(bitmaps(spark, d), ["g"])


def shared_folder(spark: SparkSession) -> str:
    """A folder all executors see: the one the cluster names; one of this machine only where all tasks run on it too."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if named:
        return named
    if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return "file://" + tempfile.mkdtemp(prefix="floorcount-")


# --- registers and encodings ---------------------------------------------------------------------------------------


@query(oracles.base("SELECT 0 AS g, l_orderkey::VARCHAR AS e FROM lineitem", 256, floors=False) + " SELECT reg, bits, lvl FROM r")
def levels_lineitem_orderkey(spark: SparkSession, d: str) -> DataFrame:
    made = levels.build_levels(load_table(spark, d, "lineitem", ["l_orderkey"]), ["l_orderkey"], m=256, kind=SQL_HASH)
    return made.select("reg", "bits", levels.highest(F.col("bits")).cast("int").alias("lvl"))


@query(oracles.base("SELECT l_suppkey AS g, l_partkey::VARCHAR AS e FROM lineitem", 64, floors=False) + " SELECT g AS l_suppkey, reg, bits FROM r")
def levels_grouped_suppkey(spark: SparkSession, d: str) -> DataFrame:
    return levels.build_levels(load_table(spark, d, "lineitem", ["l_suppkey", "l_partkey"]), ["l_partkey"], ["l_suppkey"], 64, SQL_HASH)


@query(oracles.base("SELECT 0 AS g, length(l_partkey::VARCHAR) || ':' || l_partkey::VARCHAR || length(l_suppkey::VARCHAR) || ':' || l_suppkey::VARCHAR AS e FROM lineitem", 256, floors=False) + " SELECT reg, bits FROM r")
def levels_pairs(spark: SparkSession, d: str) -> DataFrame:
    return levels.build_levels(load_table(spark, d, "lineitem", ["l_partkey", "l_suppkey"]), ["l_partkey", "l_suppkey"], m=256, kind=SQL_HASH)


@query(oracles.base(floors=False) + " SELECT g, reg, lvl FROM r")
def registers_abs6(spark: SparkSession, d: str) -> DataFrame:
    return encode.to_abs(bitmaps(spark, d), ["g"])


@query(oracles.base(m=3072, mod=True, floors=False) + " SELECT g, reg, lvl FROM r")
def registers_mod3072(spark: SparkSession, d: str) -> DataFrame:
    return encode.to_abs(bitmaps(spark, d, 3072, "mod"), ["g"])


def _floor_sql(width: int, m: int = 256) -> str:
    top = (1 << width) - 1
    return oracles.base(m=m, floors=False) + f" SELECT g, reg, f AS floor, lvl, least(lvl - f, {top}) AS \"offset\", lvl - f > {top} AS clamped FROM s JOIN k USING (g)"


for _w in (3, 4, 5):
    add(f"floor{_w}_encode", lambda spark, d, w=_w: encode.to_floor(bitmaps(spark, d, 256), ["g"], 256, w), _floor_sql(_w))


@query(oracles.base(m=3072, mod=True, floors=False) + " SELECT g, reg, f AS floor, least(lvl - f, 15) AS \"offset\" FROM s JOIN k USING (g)")
def floor4_mod_encode(spark: SparkSession, d: str) -> DataFrame:
    return encode.to_floor(bitmaps(spark, d, 3072, "mod"), ["g"], 3072, 4).select("g", "reg", "floor", "offset")


_PACKED = oracles.base(m=256, floors=False) + """, o AS (SELECT g, f AS floor, reg, least(lvl - f, 15)::BIGINT AS code FROM s JOIN k USING (g)),
p AS (SELECT g, floor, reg // 8 AS word, sum(code << (4 * (reg % 8))) AS bits FROM o GROUP BY ALL),
q AS (SELECT k.g, k.f AS floor, w, coalesce(bits, 0)::BIGINT AS bits FROM k CROSS JOIN (SELECT unnest(generate_series(0, 31)) AS w) LEFT JOIN p ON p.g = k.g AND p.word = w)
SELECT g, floor, string_agg(bits::VARCHAR, ',' ORDER BY w) AS words FROM q GROUP BY ALL"""


@query(_PACKED)
def floor4_packed_words(spark: SparkSession, d: str) -> DataFrame:
    packed = encode.pack(encode.to_floor(bitmaps(spark, d, 256), ["g"], 256), ["g"], 256)
    return packed.select("g", "floor", F.array_join(F.col("words").cast("array<string>"), ",").alias("words"))


def _fhist_sql(h: int) -> str:
    return oracles.base(m=256, floors=False) + f" SELECT g, reg, f AS floor, least(lvl - f, 15) AS \"offset\", state >> {3 - h} AS state, least(lvl - f, 15) * {1 << h} + (state >> {3 - h}) AS code FROM s JOIN k USING (g)"


for _h, _n in ((1, "fhist5"), (2, "fhist6"), (3, "fhist7")):
    add(f"{_n}_encode", lambda spark, d, h=_h: encode.to_floor_hist(bitmaps(spark, d, 256), ["g"], 256, h), _fhist_sql(_h))


@query(oracles.base(m=256, floors=False) + " SELECT g, reg, lvl, state >> 1 AS state, (lvl + 1) * 4 + (state >> 1) AS code FROM s")
def hist8_encode(spark: SparkSession, d: str) -> DataFrame:
    return encode.to_hist(bitmaps(spark, d, 256), ["g"], 2)


@query(f"WITH e AS ({oracles.STACKED}), h AS (SELECT g, cast('0x' || substr(md5(e), 1, 15) AS BIGINT) AS h FROM e WHERE e IS NOT NULL), l AS (SELECT g, (h % 256)::INT AS reg, h, length(bin(h)) - 1 AS p FROM h) SELECT g, reg, max((59 - p) * 4 + 3 - ((h >> greatest(p - 2, 0)::INT) & 3))::INT AS code FROM l GROUP BY ALL")
def registers_fractional(spark: SparkSession, d: str) -> DataFrame:
    """Eight-bit registers with two bits of a level's fraction."""
    return levels.fractional_registers(stacked(spark, d), ["e"], ["g"], 256, 2, SQL_HASH)


@query(oracles.base(floors=False) + " SELECT g, lvl, state, count(*) AS cnt FROM s GROUP BY ALL")
def tier_histogram(spark: SparkSession, d: str) -> DataFrame:
    return summaries(spark, d).select("g", F.explode("cells").alias("x")).select("g", "x.lvl", "x.state", "x.cnt")


@query(oracles.base(floors=False) + " SELECT g, t, z FROM z WHERE t <= 40")
def tier_empties(spark: SparkSession, d: str) -> DataFrame:
    cells = F.col("cells")
    each = F.transform(F.sequence(F.lit(0), F.lit(40)), lambda t: F.struct(t.alias("t"), E.below(cells, M, t).alias("z")))
    return summaries(spark, d).select("g", F.explode(each).alias("x")).select("g", "x.t", "x.z")


@query(oracles.base("SELECT user_id AS g, event_id::VARCHAR AS e FROM events", floors=False) + " SELECT g AS user_id, bit_or(CASE WHEN place = 63 THEN (-9223372036854775808)::BIGINT ELSE 1::BIGINT << place END) AS micro, bit_count(bit_or(CASE WHEN place = 63 THEN (-9223372036854775808)::BIGINT ELSE 1::BIGINT << place END))::INT AS seen FROM l GROUP BY g")
def micro64_users(spark: SparkSession, d: str) -> DataFrame:
    made = levels.build_micro(load_table(spark, d, "events", ["user_id", "event_id"]), ["event_id"], ["user_id"], M, SQL_HASH)
    return made.select("user_id", "micro", F.bit_count("micro").alias("seen"))


@query(oracles.base("SELECT 0 AS g, l_orderkey::VARCHAR AS e FROM lineitem", 256, floors=False) + ", x AS (SELECT f AS base, count(*) FILTER (WHERE lvl - f < 15) AS n_regular, count(*) FILTER (WHERE lvl - f >= 15) AS n_exceptions, coalesce(string_agg(reg || ':' || lvl, ',' ORDER BY reg) FILTER (WHERE lvl - f >= 15), '') AS exceptions FROM s CROSS JOIN k GROUP BY f) SELECT * FROM x")
def offset4_exceptions(spark: SparkSession, d: str) -> DataFrame:
    made = encode.to_exceptions(levels.build_levels(load_table(spark, d, "lineitem", ["l_orderkey"]), ["l_orderkey"], m=256, kind=SQL_HASH), m=256)
    listed = F.array_join(F.transform(F.map_entries("exceptions"), lambda x: F.concat(x["key"].cast("string"), F.lit(":"), x["value"].cast("string"))), ",")
    return made.select("base", "n_regular", "n_exceptions", F.coalesce(listed, F.lit("")).alias("exceptions"))


@query(oracles.base(m=256, floors=False) + ", y AS (SELECT g, base, count(*) FILTER (WHERE lvl < base OR lvl >= base + 7) AS n FROM s, (SELECT unnest(generate_series(0, 63))::INT AS base) GROUP BY ALL) SELECT g, arg_min(base, n * 100 + base)::INT AS base, min(n)::BIGINT AS n_exceptions FROM y GROUP BY g")
def offset3_rebase(spark: SparkSession, d: str) -> DataFrame:
    return encode.rebase(bitmaps(spark, d, 256), ["g"], 256, 3)


_REPAIR = oracles.base(m=256, floors=False) + """, c AS (SELECT g, f, reg, lvl, least(lvl, f + 7) AS stored FROM s JOIN k USING (g)),
t AS (SELECT c.*, unnest(generate_series(greatest(f, 0), f + 13))::INT AS t FROM c),
q AS (SELECT g, t, count(*) FILTER (WHERE stored >= t) AS at_least, CASE WHEN t > any_value(f) + 7 THEN floor(count(*) FILTER (WHERE stored = f + 7) / pow(2.0, t - any_value(f) - 7))::BIGINT ELSE 0 END AS ledger, count(*) FILTER (WHERE lvl >= t) AS truth FROM t GROUP BY g, t),
x AS (SELECT *, at_least + (256 - at_least) * (1 - exp(-ledger / 256.0)) AS repaired FROM q)
SELECT g, t, at_least, ledger, truth, round(repaired, 4) AS repaired, round(repaired - coalesce(lead(repaired) OVER (PARTITION BY g ORDER BY t), 0), 4) AS exactly FROM x"""


@query(_REPAIR)
def overflow_repair(spark: SparkSession, d: str) -> DataFrame:
    """Three-bit registers by tier: counted from the top, with the ledger's ghosts in the tiers above the window, and as differences, beside what the bitmap knows."""
    made = encode.repair_tiers(bitmaps(spark, d, 256), ["g"], 256, 3)
    return made.select("g", "t", "at_least", "ledger", "truth", F.round("repaired", 4).alias("repaired"), F.round("exactly", 4).alias("exactly"))


@query(oracles.base(floors=False) + " SELECT g, count(*) AS n_regs, sum(bits % 1000003)::BIGINT AS checksum FROM r GROUP BY g")
def merge_lossless(spark: SparkSession, d: str) -> DataFrame:
    """Sketches of four parts of the rows, merged: the bits of one sketch of all."""
    rows = stacked(spark, d).withColumn("part", F.pmod(F.xxhash64("e"), F.lit(4)))
    parts = [levels.build_levels(rows.filter(F.col("part") == i), ["e"], ["g"], M, SQL_HASH) for i in range(4)]
    return levels.merge_levels(*parts, by=["g"]).groupBy("g").agg(F.count(F.lit(1)).alias("n_regs"), F.sum(F.col("bits") % 1000003).alias("checksum"))


_REFRAMED = oracles.base("SELECT 0 AS g, l_orderkey::VARCHAR AS e, l_returnflag AS p FROM lineitem", 256, floors=False).replace("h AS (SELECT g,", "h AS (SELECT g, p,").replace("l AS (SELECT g,", "l AS (SELECT g, p,").replace("r AS (SELECT g, reg", "r AS (SELECT g, p, reg").split(",\ns AS")[0] + """,
f AS (SELECT p, CASE WHEN count(*) < 256 THEN -1 ELSE min(lvl) END AS f FROM r GROUP BY p), o AS (SELECT r.p, reg, f, f + least(lvl - f, 15) AS lvl FROM r JOIN f USING (p)),
j AS (SELECT reg, max(lvl) AS lvl FROM o GROUP BY reg), t AS (SELECT CASE WHEN count(*) < 256 THEN -1 ELSE min(lvl) END AS f FROM j)
SELECT f AS floor, reg, least(lvl - f, 15) AS "offset" FROM j, t"""


@query(_REFRAMED)
def merge_reframed(spark: SparkSession, d: str) -> DataFrame:
    """Packed sketches by return flag, brought to one floor."""
    rows = levels.build_levels(load_table(spark, d, "lineitem", ["l_orderkey", "l_returnflag"]), ["l_orderkey"], ["l_returnflag"], 256, SQL_HASH)
    packed = encode.pack(encode.to_floor(rows, ["l_returnflag"], 256), ["l_returnflag"], 256)
    return encode.unpack(encode.merge_packed(packed.select("floor", "words"), (), 256), (), 256).select("floor", "reg", "offset")


_PILOT = "SELECT 0 AS g, l_extendedprice::DECIMAL(18,2)::VARCHAR AS e FROM lineitem"


@query(oracles.base(_PILOT, 256, floors=False) + ", x AS (SELECT greatest(f + 1, 0) AS tight, greatest(f, 0) AS paper FROM k) SELECT count(*) AS n_rows, count(*) FILTER (WHERE lvl >= paper) AS pass_paper, count(*) FILTER (WHERE lvl >= tight) AS pass_tight, count(*) FILTER (WHERE lvl >= tight - 3) AS pass_history FROM l, x")
def exit_rate(spark: SparkSession, d: str) -> DataFrame:
    """Rows that the exit test of the finished sketch lets through, by its two bounds and with room for history."""
    rows = levels.hashed(load_table(spark, d, "lineitem", ["l_extendedprice"]), [F.col("l_extendedprice").cast("decimal(18,2)").cast("string")], (), SQL_HASH)
    floor = levels.pilot_floor(rows, 256, 60)
    keep = lambda **k: (lambda c: F.lit(True) if c is None else c)(levels.passes(F.col("h"), floor, 60, **k))
    return rows.agg(F.count(F.lit(1)).alias("n_rows"), F.count_if(keep(mode="paper")).alias("pass_paper"), F.count_if(keep()).alias("pass_tight"), F.count_if(keep(hist=3)).alias("pass_history"))


@query(oracles.base(_PILOT, 256, floors=False) + " SELECT reg, lvl, state FROM s")
def exit_pruned_equals_full(spark: SparkSession, d: str) -> DataFrame:
    """Registers of a scan pruned by the floor of a pilot, which are those of the full scan."""
    rows = load_table(spark, d, "lineitem", ["l_extendedprice", "l_returnflag"])
    cols = [F.col("l_extendedprice").cast("decimal(18,2)").cast("string")]
    return levels.registers(levels.build_levels_pruned(rows, cols, rows.filter("l_returnflag = 'R'"), 256, SQL_HASH))


SKETCHES = (1, 512, 4096, 8192)
_PRICE = "l_extendedprice::DECIMAL(18,2)::VARCHAR"
_MANY = " UNION ALL ".join(f"SELECT {k} AS n, l_partkey % {k} AS part, {_PRICE} AS e, l_returnflag = 'R' AS pilot FROM lineitem" for k in SKETCHES)
_MANY = f"""WITH e AS (SELECT n * 100000 + part AS g, n, e, pilot FROM ({_MANY})), h AS (SELECT g, n, pilot, cast('0x' || substr(md5(e), 1, 15) AS BIGINT) AS h FROM e WHERE e IS NOT NULL),
l AS (SELECT g, n, pilot, (h % 16)::INT AS reg, (60 - CASE WHEN h = 0 THEN 0 ELSE length(bin(h)) END)::INT AS lvl FROM h), r AS (SELECT g, n, reg, max(lvl) AS lvl FROM l GROUP BY ALL),
f AS (SELECT g, CASE WHEN count(*) < 16 THEN 0 ELSE min(lvl) + 1 END AS need FROM (SELECT g, reg, max(lvl) AS lvl FROM l WHERE pilot GROUP BY ALL) GROUP BY g),
p AS (SELECT n, count(*) AS n_rows, count(*) FILTER (WHERE lvl >= coalesce(need, 0)) AS n_passed FROM l LEFT JOIN f USING (g) GROUP BY n), o AS (SELECT n, count(DISTINCT g) AS n_sketches, count(*) AS n_regs, sum(lvl)::BIGINT AS levels FROM r GROUP BY n)
SELECT n::INT AS asked, n_sketches, n_rows, n_passed, n_regs, levels, levels AS levels_pruned FROM p JOIN o USING (n)"""


@query(_MANY)
def many_sketches(spark: SparkSession, d: str) -> DataFrame:
    """Prices dealt to 1, 512, 4,096 and 8,192 sketches: rows that reach the aggregate with each sketch's own floor, and its registers, with and without."""
    li = load_table(spark, d, "lineitem", ["l_partkey", "l_extendedprice", "l_returnflag"])
    price = F.col("l_extendedprice").cast("decimal(18,2)").cast("string")
    dealt = F.explode(F.array(*[F.struct(F.lit(k).alias("asked"), (F.col("l_partkey") % k).cast("int").alias("part")) for k in SKETCHES])).alias("x")
    rows = li.select(dealt, price.alias("e"), "l_returnflag").select("x.asked", "x.part", "e", "l_returnflag")
    by, m = ["asked", "part"], 16
    h = levels.hashed(rows, ["e"], by, SQL_HASH)
    first = levels.hashed(rows.filter("l_returnflag = 'R'"), ["e"], by, SQL_HASH)
    floors = levels.group_floors(first, by, m, 60)
    passed = levels.prune_by_groups(h, floors, by, 60)
    counts = h.groupBy("asked").agg(F.count(F.lit(1)).alias("n_rows")).join(passed.groupBy(F.col("asked").alias("_a")).agg(F.count(F.lit(1)).alias("n_passed")), F.col("asked") == F.col("_a")).drop("_a")

    def told(made: DataFrame, name: str) -> DataFrame:
        regs = levels.registers(made, by).select("asked", "part", "lvl")
        return regs.groupBy(F.col("asked").alias("_b")).agg(F.count_distinct("part").alias("n_sketches"), F.count(F.lit(1)).alias("n_regs"), F.sum("lvl").alias(name))

    of = lambda r: levels.levels_of(r, by, m, 60)
    # what passes is added to the pilot's sketches, whose registers at their floors it may not reach
    full, pruned = told(of(h), "levels"), told(levels.merge_levels(of(first), of(passed), by=by), "levels_pruned").select(F.col("_b").alias("_c"), "levels_pruned")
    out = counts.join(full, F.col("asked") == F.col("_b")).join(pruned, F.col("asked") == F.col("_c"))
    return out.select("asked", "n_sketches", "n_rows", "n_passed", "n_regs", "levels", "levels_pruned")


# --- estimators ----------------------------------------------------------------------------------------------------

_T, _HL, _LY = oracles.tlc(), oracles.hist_lc(), oracles.layered()
_ESTIMATES = {
    "lc": oracles.estimate("lc", "lc", "b"),
    "lc_floor": oracles.estimate("lc_floor", "lcf", "b"),
    "tlc_best": oracles.estimate("tlc_best", "v", "x", "d AS (SELECT *, abs(z - 512) AS far FROM z WHERE z > 0 AND z < 2048)", "x AS (SELECT d.g, avg(pow(2.0, t) * 2048 * ln(2048.0 / z)) AS v FROM d JOIN (SELECT g, min(far) AS far FROM d GROUP BY g) n ON n.g = d.g AND n.far = d.far GROUP BY d.g)"),
    "tlc": oracles.estimate("tlc", "tlc", "t", _T),
    "occ_mean": oracles.estimate("occ_mean", "(c + 2048) / 4096.0 * 2 * c * c / s", "k"),
    "harm_mean": oracles.estimate("harm_mean", f"{E.alpha(2048)!r} * 2 * c * c / s", "k"),
    "geo_mean": oracles.estimate("geo_mean", "2 * pow(2.0, mean) * (c + 2048) / 4096.0", "k"),
    "hll": oracles.estimate("hll", "CASE WHEN z0 > 0 AND raw <= 2.5 * 2048 THEN lc ELSE raw END", "x", f"x AS (SELECT *, {E.alpha(2048)!r} ::DOUBLE * 2 * 2048 * 2048 / (s + 2.0 * z0) AS raw FROM b)"),
    "hybrid": oracles.estimate("hybrid", "hybrid", "y0", oracles.mean_h(0), oracles.hybrid(0)),
    "hybrid_h2": oracles.estimate("hybrid_h2", "hybrid", "y2", oracles.mean_h(2), oracles.hybrid(2)),
    "hist_lc": oracles.estimate("hist_lc", "hist_lc", "hl", _HL),
    "tlc_layered": oracles.estimate("tlc_layered", "tlc_layered", "ly", _T, _HL, _LY),
    "hybrid_layered": oracles.estimate("hybrid_layered", "0.5 * tlc_layered + 0.5 * hybrid", "(SELECT ly.g, tlc_layered, hybrid FROM ly JOIN y2 ON ly.g = y2.g)", _T, _HL, _LY, oracles.mean_h(2), oracles.hybrid(2)),
    "gra": oracles.estimate("gra", "gra", "ga", oracles.gra()),
    "loglog": oracles.estimate("loglog", "2048 * pow(2.0, (c * mean + c) / 2048.0)", "k"),
    "loglog_trunc": oracles.estimate("loglog_trunc", "v", "x", "a AS (SELECT g, reg, lvl FROM s UNION ALL SELECT g, -1, -1 FROM k, (SELECT unnest(generate_series(1, 2048)) AS i) WHERE i <= z0)", "q AS (SELECT g, lvl, row_number() OVER (PARTITION BY g ORDER BY lvl) AS r FROM a)", "x AS (SELECT g, 2048 * pow(2.0, sum(lvl + 1) / 1433.0) AS v FROM q WHERE r <= 1433 GROUP BY g)"),
}
for _h in (1, 2, 3):
    _ESTIMATES[f"mean_h{_h}"] = oracles.estimate(f"mean_h{_h}", "mean", f"m{_h}", oracles.mean_h(_h))


for _h in (1, 3):
    _ESTIMATES[f"tlc_layered_h{_h}"] = oracles.estimate(f"tlc_layered_h{_h}", "tlc_layered", "ly", _T, oracles.hist_lc(_h), _LY)


def _estimate(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: summaries(spark, d).select("g", F.round(E.ESTIMATORS[name](F.col("cells"), M), 4).alias(name))


for _n in E.ESTIMATORS:
    add(f"est_{_n}", _estimate(_n), _ESTIMATES.get(_n))


@query(oracles.base() + ", n AS (SELECT g, count(DISTINCT e) AS n_distinct FROM e GROUP BY g)," + oracles.chain(_T, _HL, _LY, oracles.mean_h(0), oracles.hybrid(0)) + " SELECT n.g, n_distinct, round(lc, 4) AS lc, round(tlc, 4) AS tlc, round(hybrid, 4) AS hybrid, round(tlc_layered, 4) AS tlc_layered FROM n JOIN b USING (g) JOIN t USING (g) JOIN y0 USING (g) JOIN ly USING (g)")
def est_all(spark: SparkSession, d: str) -> DataFrame:
    """The flagship: one scan of lineitem, one sketch a key, several estimates of each, beside the exact counts."""
    c = F.col("cells")
    est = summaries(spark, d).select("g", *[F.round(E.ESTIMATORS[k](c, M), 4).alias(k) for k in ("lc", "tlc", "hybrid", "tlc_layered")])
    exact = stacked(spark, d).groupBy(F.col("g").alias("_g")).agg(F.count_distinct("e").alias("n_distinct"))
    return est.join(exact, F.col("g") == F.col("_g")).drop("_g")


@query(oracles.base() + " SELECT g, t, round(pow(2.0, t) * 2048 * ln(2048.0 / z), 4) AS estimate FROM z WHERE t <= 19 AND z > 0 AND z < 2048")
def est_tlc_at(spark: SparkSession, d: str) -> DataFrame:
    each = F.explode(F.array(*[F.struct(F.lit(t).alias("t"), E.est_tlc_at(F.col("cells"), M, t).alias("v")) for t in range(20)])).alias("x")
    return summaries(spark, d).select("g", each).filter("x.v is not null").select("g", "x.t", F.round("x.v", 4).alias("estimate"))


@query("SELECT user_id, seen, round(64 * ln(64 / greatest(64 - seen, 0.5)), 4) AS estimate FROM (" + SQL["micro64_users"] + ")")
def est_micro(spark: SparkSession, d: str) -> DataFrame:
    return micro64_users(spark, d).select("user_id", "seen", F.round(E.est_micro(F.col("micro")), 4).alias("estimate"))


_FLOORS = oracles.base("SELECT event_type AS g, user_id::VARCHAR AS e FROM events", 256) + ", y AS (SELECT g, bit_count(bit_or(CASE WHEN place = 63 THEN (-9223372036854775808)::BIGINT ELSE 1::BIGINT << place END)) AS pop FROM l GROUP BY g), x AS (SELECT g, count(*) + sum(bit_count((state >> 1)::BIGINT)) AS seen FROM s GROUP BY g) SELECT b.g AS event_type, round(greatest(lc, pop, seen), 4) AS estimate FROM b JOIN y USING (g) JOIN x USING (g)"


@query(_FLOORS)
def est_floor_rules(spark: SparkSession, d: str) -> DataFrame:
    """Linear counting, at least what the small bitmap, and registers with their history, have seen."""
    ev = load_table(spark, d, "events", ["event_type", "user_id"])
    micro = levels.build_micro(ev, ["user_id"], ["event_type"], 256, SQL_HASH).withColumnRenamed("event_type", "_t")
    full = levels.summarize(levels.build_levels(ev, ["user_id"], ["event_type"], 256, SQL_HASH), ["event_type"]).join(micro, F.col("event_type") == F.col("_t"))
    return full.select("event_type", F.round(E.est_lc_with_floors(F.col("cells"), 256, F.col("micro"), 2), 4).alias("estimate"))


@query(oracles.base(floors=False) + ", u AS (SELECT g, reg, (SELECT min(i) FROM generate_series(0, 62) x(i) WHERE ((bits >> i::INT) & 1) = 0) AS low FROM r) SELECT g, round(2048 / 0.77351 * pow(2.0, sum(low) / 2048.0), 4) AS estimate FROM u GROUP BY g")
def est_pcsa(spark: SparkSession, d: str) -> DataFrame:
    """Probabilistic counting: the mean place of the lowest level that was never seen."""
    unseen = F.bitwise_not(F.col("bits"))
    low = F.bit_count(unseen.bitwiseAND(F.negate(unseen)) - 1)
    return bitmaps(spark, d).groupBy("g").agg(F.round(F.lit(M / 0.77351) * F.pow(F.lit(2.0), F.sum(low) / F.lit(float(M))), 4).alias("estimate"))


@query("SELECT o_custkey, n, n / pow(2.0, k) AS inside, k::INT AS octaves FROM (SELECT *, greatest(ceil(log2(n / 1000000.0)), 0) AS k FROM (SELECT o_custkey, sum(o_totalprice::DECIMAL(18,2))::DOUBLE AS n FROM orders GROUP BY 1))")
def cf_fold(spark: SparkSession, d: str) -> DataFrame:
    """Customers' totals halved until a table that ends at a million holds them."""
    df = load_table(spark, d, "orders", ["o_custkey", "o_totalprice"]).groupBy("o_custkey").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("n"))
    inside, k = E.fold(F.col("n"), 1e6)
    return df.select("o_custkey", "n", inside.alias("inside"), k.cast("int").alias("octaves"))


#: Bounds of a place of 60 bits: each step holds a tenth more of the rows than the one before, the last all of them.
_SWEEP = [round(2**60 * 1.1 ** (i - 150)) for i in range(151)]
_SWEPT = f"""SELECT step AS g, e FROM (SELECT o_orderkey::VARCHAR AS e, cast('0x' || substr(md5('place' || o_orderkey::VARCHAR), 1, 15) AS BIGINT) AS place FROM orders WHERE o_orderkey IS NOT NULL),
(SELECT unnest(generate_series(0, 150))::INT AS step, unnest({_SWEEP}) AS bound) WHERE place < bound"""


@query(oracles.base(_SWEPT, floors=False) + ", " + oracles.mean_h(0) + " SELECT g AS step, round(mean, 4) AS corrected FROM m0")
def cf_range_lookup(spark: SparkSession, d: str) -> DataFrame:
    """The correction over a sweep of raw estimates, of the order keys growing by a tenth a step: an index into an array instead of a range join."""
    keys = order_keys(spark, d)
    place = H.hash_key([F.concat(F.lit("place"), F.col("o_orderkey").cast("string"))], SQL_HASH)
    first = keys.select("o_orderkey", place.alias("place")).select("o_orderkey", sum([(F.col("place") >= F.lit(b)).cast("int") for b in _SWEEP[:-1]], F.lit(0)).alias("first"))
    made = levels.build_levels(first, ["o_orderkey"], ["first"], M, SQL_HASH)
    grown = made.select(F.explode(F.sequence("first", F.lit(150))).alias("step"), "reg", "bits").groupBy("step", "reg").agg(F.bit_or("bits").alias("bits"))
    raw = levels.summarize(grown, ["step"]).select("step", E.est_occ_mean(F.col("cells"), M).alias("raw"))
    return raw.select("step", F.round(E.corrected(F.col("raw"), M), 4).alias("corrected"))


@query("SELECT l_suppkey, m, round(m * ln(2.0 * m) / 256, 4) AS ghosts, round(pow(2.0, -16), 8) AS overflow_4, round(1.04 / sqrt(m), 6) AS standard_error, round(m * 8 * ln(m), 4) AS third_promotion FROM (SELECT l_suppkey, greatest(1::BIGINT << (length(bin(count(*))) - 1)::INT, 16)::BIGINT AS m FROM lineitem GROUP BY 1)")
def laws(spark: SparkSession, d: str) -> DataFrame:
    """Closed forms for a sketch a supplier, with registers by its rows: ghost overflow, chance of overflow, standard error, elements at a promotion."""
    held = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.length(F.bin(F.count(F.lit(1)))) - 1)
    m = F.col("m")
    sized = load_table(spark, d, "lineitem", ["l_suppkey"]).groupBy("l_suppkey").agg(F.greatest(held, F.lit(16).cast("bigint")).alias("m"))
    return sized.select("l_suppkey", "m", F.round(m * F.ln(2.0 * m) / 256, 4).alias("ghosts"), F.round(F.pow(F.lit(2.0), F.lit(-16)), 8).alias("overflow_4"), F.round(1.04 / F.sqrt(m), 6).alias("standard_error"), F.round(m * 8 * F.ln(m), 4).alias("third_promotion"))


# --- measures ------------------------------------------------------------------------------------------------------

_POINTS = """p AS (SELECT unnest([200, 1000, 3000, 7000, 10000, 15000]) AS checkpoint, unnest([1, 2, 3, 4, 5, 6]) AS i)"""
_GROWING = f"WITH RECURSIVE {_POINTS}, e AS (SELECT salt * 100 + i AS g, salt || ':' || o_orderkey AS e FROM orders, p, (SELECT unnest(generate_series(1, 8)) AS salt) WHERE o_orderkey <= checkpoint),\n"
_CURVE = _GROWING + oracles.base("SELECT 0 AS g, '' AS e", 256).split(",\n", 1)[1].replace("WITH RECURSIVE ", "") + "," + oracles.tlc(256) + ", q AS (SELECT checkpoint, (tlc - n) / n AS signed FROM t JOIN p ON t.g % 100 = p.i JOIN (SELECT g, count(*) AS n FROM e GROUP BY g) c USING (g)), m AS (SELECT checkpoint, count(*) AS runs, avg(abs(signed)) AS mae, avg(signed) AS bias, stddev_pop(signed) AS deviation FROM q GROUP BY checkpoint)"
_STEPS = (200, 1000, 3000, 7000, 10000, 15000)


def error_curve(spark: SparkSession, d: str) -> DataFrame:
    """Rows (checkpoint, runs, mae, bias, deviation): growing prefixes of the order keys, hashed anew for each of eight runs."""
    orders = load_table(spark, d, "orders", ["o_orderkey"])
    grown = orders.select("o_orderkey", F.explode(F.array(*[F.lit(c) for c in _STEPS])).alias("checkpoint")).filter("o_orderkey <= checkpoint")
    salted = grown.select("checkpoint", F.explode(F.sequence(F.lit(1), F.lit(8))).alias("run"), "o_orderkey")
    keyed = salted.select("checkpoint", "run", F.concat_ws(":", F.col("run").cast("string"), F.col("o_orderkey").cast("string")).alias("e"))
    truth = keyed.groupBy(F.col("checkpoint").alias("_c"), F.col("run").alias("_r")).agg(F.count(F.lit(1)).alias("truth"))
    est = sets.estimate(levels.build_levels(keyed, ["e"], ["checkpoint", "run"], 256, SQL_HASH), ["checkpoint", "run"], 256)
    return measures.by_checkpoint(measures.with_errors(est.join(truth, (F.col("checkpoint") == F.col("_c")) & (F.col("run") == F.col("_r"))), "truth", "tlc"))


@query(_CURVE + " SELECT checkpoint, runs, round(mae, 4) AS mae, round(bias, 4) AS bias, round(deviation, 4) AS deviation FROM m")
def error_metrics(spark: SparkSession, d: str) -> DataFrame:
    return error_curve(spark, d).select("checkpoint", "runs", *[F.round(c, 4).alias(c) for c in ("mae", "bias", "deviation")])


@query(_CURVE + ", cw AS (SELECT *, checkpoint - coalesce(lag(checkpoint) OVER (ORDER BY checkpoint), 0) AS width FROM m) SELECT round(max(mae), 4) AS peak, round(avg(mae), 4) AS by_log, round(sum(mae * checkpoint) / sum(checkpoint), 4) AS by_size, round(sum(mae * width) / sum(width), 4) AS by_width FROM cw")
def weighted_error(spark: SparkSession, d: str) -> DataFrame:
    return measures.weighted(error_curve(spark, d)).select(*[F.round(c, 4).alias(c) for c in ("peak", "by_log", "by_size", "by_width")])


_SPECS = ", ".join(f"('{k}', {v[0]}, {v[1] or 0}, {v[2] or 0})" for k, v in sorted(measures.SPECS.items()))


@query(f"WITH s(spec, bits, per, word) AS (VALUES {_SPECS}), m AS (SELECT unnest([1024, 2048, 2560, 3072, 3584, 4096]) AS m), x AS (SELECT *, CASE WHEN per = 0 THEN ceil(m * bits / 8) ELSE ceil(m / greatest(per, 1)) * word / 8 END::BIGINT AS bytes FROM s, m) SELECT spec, m, bits, bytes, bytes + 28 AS with_state, round(bytes / (m * 6 / 8), 4) AS relative, round(CASE WHEN per = 0 THEN 1.0 ELSE bits * per / greatest(word, 1) END, 4) AS efficiency, sketches, bytes * sketches AS total FROM x, (SELECT count(DISTINCT l_suppkey) AS sketches FROM lineitem)")
def memory_table(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of a sketch of every type and size, and of one for each supplier."""
    held = load_table(spark, d, "lineitem", ["l_suppkey"]).agg(F.count_distinct("l_suppkey").alias("sketches"))
    return measures.memory_table(spark).crossJoin(F.broadcast(held)).withColumn("total", F.col("bytes") * F.col("sketches"))  # one row


@query("WITH n(spec, bits) AS (VALUES ('abs6', 6), ('floor4', 4), ('fhist6', 6)), x AS (SELECT unnest([1e6, 1e9, 1e12, 1e18]) AS largest) SELECT spec, largest, CASE WHEN spec = 'abs6' THEN 2048 * greatest(bits, ceil(log2(log2(greatest(largest / 2048, 1)) + 11 + 3))) ELSE bits * 2048 + ceil(log2(log2(greatest(largest / 2048, 1)) + 11 + 3)) END::BIGINT AS bits_needed FROM n, x")
def size_law(spark: SparkSession, d: str) -> DataFrame:
    """Bits to count up to a number: registers that must hold every level against a shared floor."""
    rows = [(s, n, int(measures.size_law(s, M, n))) for s in ("abs6", "floor4", "fhist6") for n in (1e6, 1e9, 1e12, 1e18)]
    return spark.createDataFrame(rows, "spec string, largest double, bits_needed long")


# --- workloads on tables -------------------------------------------------------------------------------------------


@query("SELECT count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def exact_multi(spark: SparkSession, d: str) -> DataFrame:
    return load_table(spark, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT l_returnflag, count(DISTINCT (l_partkey, l_suppkey)) AS n_distinct FROM lineitem GROUP BY 1")
def exact_distinct(spark: SparkSession, d: str) -> DataFrame:
    return sets.exact_distinct(load_table(spark, d, "lineitem"), ["l_partkey", "l_suppkey"], ["l_returnflag"])


@query("SELECT count(DISTINCT l_suppkey) AS n_distinct FROM lineitem")
def exact_bitmap(spark: SparkSession, d: str) -> DataFrame:
    return sets.exact_tiny(load_table(spark, d, "lineitem", ["l_suppkey"]), "l_suppkey")


_SHINGLES = "SELECT {g} AS g, substr(text, i, 31) AS e FROM (SELECT {g}, text, unnest(generate_series(1, length(text) - 30)) AS i FROM {t} WHERE length(text) >= 31)"


@query(oracles.base(_SHINGLES.format(g="lang", t="documents"), 2048) + "," + oracles.tlc() + " SELECT g AS lang, round(tlc, 4) AS estimate FROM t")
def shingle_cardinality(spark: SparkSession, d: str) -> DataFrame:
    made = shingles.shingle_levels(load_table(spark, d, "documents", ["lang", "text"]), "text", ["lang"], M, kind=SQL_HASH)
    return sets.estimate(made, ["lang"]).select("lang", F.round("tlc", 4).alias("estimate"))


@query()
def shingle_cardinality_rolling(spark: SparkSession, d: str) -> DataFrame:
    """The same by the rolling hash that production takes."""
    made = shingles.shingle_levels(load_table(spark, d, "documents", ["lang", "text"]), "text", ["lang"], M)
    return sets.estimate(made, ["lang"]).select("lang", F.round("tlc", 4).alias("estimate"))


_QC = oracles.base("SELECT x AS g, e FROM (" + _SHINGLES.format(g="doc_id", t="documents") + ") q LEFT JOIN labels l ON l.doc_id = q.g, (SELECT unnest(['in', 'out']) AS x) WHERE x = 'in' OR quality = 1")


@query(_QC + "," + oracles.tlc() + " SELECT max(round(tlc, 4)) FILTER (WHERE g = 'in') AS before_filter, max(round(tlc, 4)) FILTER (WHERE g = 'out') AS after_filter FROM t")
def qc_in_out_docs(spark: SparkSession, d: str) -> DataFrame:
    """Shingles before and after a quality filter: one scan, one hash, two bitmaps a register."""
    docs = load_table(spark, d, "documents", ["doc_id", "text"]).join(load_table(spark, d, "labels", ["doc_id", "quality"]), "doc_id", "left")
    kept = docs.select("text", F.coalesce(F.col("quality") == 1, F.lit(False)).alias("k"))
    regs = shingles.shingle_levels(kept, "text", ["k"], M, kind=SQL_HASH)
    return _before_after(regs.groupBy("reg").agg(F.bit_or("bits").alias("bits"), F.bit_or(F.when(F.col("k"), F.col("bits"))).alias("kept")))


def _in_out(rows: DataFrame, e: str, keep) -> DataFrame:
    h = rows.select(H.hash_key([e], SQL_HASH).alias("h"), F.coalesce(keep, F.lit(False)).alias("k"))
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), H.level_of(F.col("h"), 60))
    regs = h.groupBy(H.register_of(F.col("h"), M).alias("reg")).agg(F.bit_or(bit).alias("bits"), F.bit_or(F.when(F.col("k"), bit)).alias("kept"))
    return _before_after(regs)


def _before_after(regs: DataFrame) -> DataFrame:
    one = lambda c: levels.summarize(regs.filter(F.col(c).isNotNull()).select("reg", F.col(c).alias("bits"))).select(F.round(E.est_tlc(F.col("cells"), M), 4))
    return one("bits").toDF("before_filter").crossJoin(one("kept").toDF("after_filter"))  # one row each


@query(oracles.base("SELECT x AS g, l_extendedprice::DECIMAL(18,2)::VARCHAR AS e FROM lineitem, (SELECT unnest(['in', 'out']) AS x) WHERE x = 'in' OR l_returnflag = 'R'") + "," + oracles.tlc() + " SELECT max(round(tlc, 4)) FILTER (WHERE g = 'in') AS before_filter, max(round(tlc, 4)) FILTER (WHERE g = 'out') AS after_filter FROM t")
def qc_in_out_lineitem(spark: SparkSession, d: str) -> DataFrame:
    rows = load_table(spark, d, "lineitem", ["l_extendedprice", "l_returnflag"]).select(F.col("l_extendedprice").cast("decimal(18,2)").cast("string").alias("e"), "l_returnflag")
    return _in_out(rows, "e", F.col("l_returnflag") == "R")


def _simple(source: str, m: int, name: str) -> str:
    return oracles.base(source, m) + "," + oracles.tlc(m) + f" SELECT g AS {name}, round(tlc, 4) AS estimate FROM t"


def _counted(df: DataFrame, cols: list, by: str, m: int) -> DataFrame:
    return sets.estimate(levels.build_levels(df, cols, [by], m, SQL_HASH), [by], m).select(by, F.round("tlc", 4).alias("estimate"))


@query(_simple("SELECT date_trunc('hour', ts) AS g, user_id::VARCHAR AS e FROM events", 64, "hour"))
def grouped_users_hour(spark: SparkSession, d: str) -> DataFrame:
    return _counted(load_table(spark, d, "events", ["ts", "user_id"]).withColumn("hour", F.date_trunc("hour", "ts").cast("timestamp_ntz")), ["user_id"], "hour", 64)


@query(_simple("SELECT date_trunc('month', o_orderdate) AS g, o_custkey::VARCHAR AS e FROM orders", 256, "month"))
def orders_per_month(spark: SparkSession, d: str) -> DataFrame:
    return _counted(load_table(spark, d, "orders", ["o_orderdate", "o_custkey"]).withColumn("month", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz")), ["o_custkey"], "month", 256)


def _cube_sql(sets_: str) -> str:
    src = f"SELECT coalesce(l_returnflag, '') || '|' || coalesce(l_linestatus, '') || '|' || gid AS g, e FROM (SELECT CASE WHEN gid & 2 = 0 THEN l_returnflag END AS l_returnflag, CASE WHEN gid & 1 = 0 THEN l_linestatus END AS l_linestatus, gid, l_partkey::VARCHAR AS e FROM lineitem, (SELECT unnest({sets_}) AS gid))"
    return oracles.base(src, 256) + "," + oracles.tlc(256) + " SELECT nullif(split_part(g, '|', 1), '') AS l_returnflag, nullif(split_part(g, '|', 2), '') AS l_linestatus, split_part(g, '|', 3)::INT AS gid, round(tlc, 4) AS estimate FROM t"


def _cube(spark: SparkSession, d: str, sets_: list | None) -> DataFrame:
    dims = ["l_returnflag", "l_linestatus"]
    return sets.rollup_sketch(load_table(spark, d, "lineitem", [*dims, "l_partkey"]), ["l_partkey"], dims, 256, SQL_HASH, sets_).withColumn("estimate", F.round("estimate", 4))


add("rollup_sketch", lambda spark, d: _cube(spark, d, None), _cube_sql("[0, 1, 3]"))
add("cube_sketch", lambda spark, d: _cube(spark, d, sets.cube_sets(["l_returnflag", "l_linestatus"])), _cube_sql("[0, 1, 2, 3]"))
add("grouping_sets_sketch", lambda spark, d: _cube(spark, d, [["l_returnflag"], ["l_linestatus"]]), _cube_sql("[1, 2]"))


@query(_simple("SELECT w AS g, user_id::VARCHAR AS e FROM (SELECT time_bucket(INTERVAL '15 minutes', ts) - INTERVAL '15 minutes' * i AS w, user_id FROM events, (SELECT unnest(generate_series(0, 3)) AS i))", 64, "start"))
def sliding_users(spark: SparkSession, d: str) -> DataFrame:
    """Distinct users of every hour that starts at a quarter."""
    ev = load_table(spark, d, "events", ["ts", "user_id"]).withColumn("start", F.window(F.col("ts").cast("timestamp"), "1 hour", "15 minutes")["start"].cast("timestamp_ntz"))
    return _counted(ev, ["user_id"], "start", 64)


@query("WITH x AS (SELECT user_id, ts, event_type, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '30 minutes' THEN 0 ELSE 1 END AS new FROM events), y AS (SELECT user_id, ts, event_type, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM x) SELECT user_id, min(ts) AS start, count(*) AS n_events, bit_count(bit_or(1::BIGINT << ((cast('0x' || substr(md5(event_type), 1, 15) AS BIGINT) >> 11) & 63)::INT))::INT AS seen FROM y GROUP BY user_id, k")
def session_users(spark: SparkSession, d: str) -> DataFrame:
    """Sessions by user with a gap of half an hour; event types in each by the bitmap of 64."""
    ev = load_table(spark, d, "events", ["ts", "user_id", "event_type"]).withColumn("ts", F.col("ts").cast("timestamp"))
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), H.micro_place(H.hash_key(["event_type"], SQL_HASH), M))
    out = ev.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n_events"), F.bit_count(F.bit_or(bit)).alias("seen"))
    return out.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n_events", "seen")


_DAYS = "SELECT d AS g, user_id::VARCHAR AS e FROM (SELECT DISTINCT ts::DATE AS d FROM events) JOIN events ON ts::DATE <= d"


def running(spark: SparkSession, d: str) -> DataFrame:
    ev = load_table(spark, d, "events", ["ts", "user_id"]).select(F.to_date("ts").alias("day"), "user_id")
    run = sets.running_levels(levels.build_levels(ev, ["user_id"], ["day"], 256, SQL_HASH), "day")
    return sets.estimate(run, ["day"], 256)


@query(_simple(_DAYS, 256, "day"))
def running_distinct(spark: SparkSession, d: str) -> DataFrame:
    """Distinct users up to each day."""
    return running(spark, d).select("day", F.round("tlc", 4).alias("estimate"))


@query(oracles.base(_DAYS, 256) + "," + oracles.tlc(256) + " SELECT g AS day, round(tlc - coalesce(lag(tlc) OVER (ORDER BY g), 0), 4) AS fresh FROM t")
def daily_delta(spark: SparkSession, d: str) -> DataFrame:
    """How much each day adds to the distinct users."""
    return running(spark, d).select("day", F.round(F.col("tlc") - F.coalesce(F.lag("tlc").over(W.orderBy("day")), F.lit(0.0)), 4).alias("fresh"))  # a row a day


_PAIRS = oracles.base("SELECT event_type AS g, user_id::VARCHAR AS e FROM events UNION ALL SELECT a.t || '+' || b.t, user_id::VARCHAR FROM events JOIN (SELECT DISTINCT event_type AS t FROM events) a ON true JOIN (SELECT DISTINCT event_type AS t FROM events) b ON a.t < b.t WHERE event_type IN (a.t, b.t)", 256) + "," + oracles.tlc(256)


@query(_PAIRS + " SELECT x.g AS a, y.g AS b, round(u.tlc, 4) AS union_estimate, round(greatest(x.tlc + y.tlc - u.tlc, 0), 4) AS intersection_estimate, round(greatest(x.tlc + y.tlc - u.tlc, 0) / u.tlc, 4) AS jaccard_estimate FROM t x JOIN t y ON x.g < y.g JOIN t u ON u.g = x.g || '+' || y.g")
def union_intersection_users(spark: SparkSession, d: str) -> DataFrame:
    made = levels.build_levels(load_table(spark, d, "events", ["event_type", "user_id"]), ["user_id"], ["event_type"], 256, SQL_HASH)
    out = sets.pair_estimates(made, "event_type", 256)
    return out.select("a", "b", *[F.round(c, 4).alias(c) for c in ("union_estimate", "intersection_estimate", "jaccard_estimate")])


@query(oracles.base("SELECT l_suppkey AS g, l_partkey::VARCHAR AS e FROM lineitem", 256) + "," + oracles.tlc(256) + " SELECT g AS l_suppkey, round(tlc, 4) AS estimate FROM t ORDER BY tlc DESC, g LIMIT 10")
def topk_suppliers_by_parts(spark: SparkSession, d: str) -> DataFrame:
    """The ten suppliers of the most parts: a report."""
    made = levels.build_levels(load_table(spark, d, "lineitem", ["l_suppkey", "l_partkey"]), ["l_partkey"], ["l_suppkey"], 256, SQL_HASH)
    return sets.estimate(made, ["l_suppkey"], 256).orderBy(F.desc("tlc"), "l_suppkey").limit(10).select("l_suppkey", F.round("tlc", 4).alias("estimate"))


@query(_simple("SELECT p_brand AS g, o_custkey::VARCHAR AS e FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey", 256, "p_brand"))
def join_customers_per_brand(spark: SparkSession, d: str) -> DataFrame:
    li, o, p = load_table(spark, d, "lineitem", ["l_orderkey", "l_partkey"]), load_table(spark, d, "orders", ["o_orderkey", "o_custkey"]), load_table(spark, d, "part", ["p_partkey", "p_brand"])
    joined = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return _counted(joined.select("p_brand", "o_custkey"), ["o_custkey"], "p_brand", 256)


@query(_simple("SELECT n_name AS g, c_custkey::VARCHAR AS e FROM customer JOIN nation ON c_nationkey = n_nationkey", 256, "n_name"))
def customers_per_nation(spark: SparkSession, d: str) -> DataFrame:
    c, n = load_table(spark, d, "customer", ["c_custkey", "c_nationkey"]), load_table(spark, d, "nation", ["n_nationkey", "n_name"])
    return _counted(c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "c_custkey"), ["c_custkey"], "n_name", 256)


@query("SELECT count(DISTINCT c_custkey) AS n_customers FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def semi_customers(spark: SparkSession, d: str) -> DataFrame:
    c, o = load_table(spark, d, "customer", ["c_custkey"]), load_table(spark, d, "orders", ["o_custkey"])
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").agg(F.count_distinct("c_custkey").alias("n_customers"))


@query("SELECT count(DISTINCT c_custkey) AS n_customers FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000)")
def anti_customers(spark: SparkSession, d: str) -> DataFrame:
    c, o = load_table(spark, d, "customer", ["c_custkey"]), load_table(spark, d, "orders", ["o_custkey", "o_totalprice"]).filter("o_totalprice > 100000")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").agg(F.count_distinct("c_custkey").alias("n_customers"))


_HALVES = "SELECT DISTINCT o_custkey AS k FROM orders WHERE o_orderdate {} TIMESTAMP '1995-01-01'"


@query(f"SELECT 'both' AS kind, count(*) AS n FROM ({_HALVES.format('<')} INTERSECT {_HALVES.format('>=')}) UNION ALL SELECT 'either', count(*) FROM ({_HALVES.format('<')} UNION {_HALVES.format('>=')}) UNION ALL SELECT 'first only', count(*) FROM ({_HALVES.format('<')} EXCEPT {_HALVES.format('>=')})")
def setops_customers(spark: SparkSession, d: str) -> DataFrame:
    o = load_table(spark, d, "orders", ["o_custkey", "o_orderdate"])
    cut = F.lit("1995-01-01").cast("timestamp_ntz")
    a, b = o.filter(F.col("o_orderdate") < cut).select("o_custkey"), o.filter(F.col("o_orderdate") >= cut).select("o_custkey")
    count = lambda kind, df: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
    return count("both", a.intersect(b)).unionAll(count("either", a.union(b).distinct())).unionAll(count("first only", a.distinct().exceptAll(b.distinct())))


@query("SELECT event_type, count(DISTINCT user_id) FILTER (WHERE extract(hour FROM ts) < 12) AS am, count(DISTINCT user_id) FILTER (WHERE extract(hour FROM ts) >= 12) AS pm FROM events GROUP BY 1")
def pivot_users(spark: SparkSession, d: str) -> DataFrame:
    ev = load_table(spark, d, "events", ["ts", "event_type", "user_id"]).withColumn("half", F.when(F.hour("ts") < 12, "am").otherwise("pm"))
    return ev.groupBy("event_type").pivot("half", ["am", "pm"]).agg(F.count_distinct("user_id"))


@query("WITH h AS (SELECT date_trunc('hour', ts) AS hour, count(DISTINCT user_id) AS n FROM events GROUP BY 1), c AS (SELECT TIMESTAMP '2024-01-01 00:00:00' + INTERVAL '7 hours' * i + INTERVAL '30 minutes' AS at_ FROM (SELECT unnest(generate_series(0, 60)) AS i)) SELECT at_ AS checkpoint, n AS users FROM c ASOF LEFT JOIN h ON c.at_ >= h.hour")
def asof_snapshot(spark: SparkSession, d: str) -> DataFrame:
    """The last hourly count at or before each checkpoint: both sides in one ordered union, a running last value; days are the partitions' carry."""
    hourly = load_table(spark, d, "events", ["ts", "user_id"]).groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("at")).agg(F.count_distinct("user_id").alias("n"))
    points = spark.range(61).select((F.lit("2024-01-01 00:30:00").cast("timestamp") + F.make_interval(hours=(F.col("id") * 7).cast("int"))).cast("timestamp_ntz").alias("at"))
    both = hourly.select("at", "n", F.lit(0).alias("asks")).unionAll(points.select("at", F.lit(None).cast("bigint").alias("n"), F.lit(1).alias("asks")))
    last = F.last("n", ignorenulls=True).over(W.orderBy("at", "asks").rowsBetween(W.unboundedPreceding, W.currentRow))  # a row an hour
    return both.withColumn("users", last).filter("asks = 1").select(F.col("at").alias("checkpoint"), "users")


@query(_simple("SELECT 0 AS g, regexp_extract(url, '^https?://([^/]+)', 1) AS e FROM pages", 256, "part"))
def url_hosts(spark: SparkSession, d: str) -> DataFrame:
    return _counted(load_table(spark, d, "pages", ["url"]).select(F.lit(0).alias("part"), F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("e")), ["e"], "part", 256)


@query(_simple("SELECT 0 AS g, array_to_string(list_transform(embedding, lambda x: CASE WHEN x >= 0 THEN '1' ELSE '0' END), '') AS e FROM embeddings", 256, "part"))
def embedding_sign_patterns(spark: SparkSession, d: str) -> DataFrame:
    sign = F.array_join(F.transform("embedding", lambda x: F.when(x >= 0, "1").otherwise("0")), "")
    return _counted(load_table(spark, d, "embeddings", ["embedding"]).select(F.lit(0).alias("part"), sign.alias("e")), ["e"], "part", 256)


@query(_simple("SELECT lang AS g, text AS e FROM documents", 256, "lang"))
def lang_distinct_texts(spark: SparkSession, d: str) -> DataFrame:
    return _counted(load_table(spark, d, "documents", ["lang", "text"]), ["text"], "lang", 256)


@query(_simple("SELECT event_type AS g, props->>'$.k' AS e FROM events", 64, "event_type"))
def json_key_cardinality(spark: SparkSession, d: str) -> DataFrame:
    ev = load_table(spark, d, "events", ["event_type", "props"]).select("event_type", F.get_json_object("props", "$.k").alias("e"))
    return _counted(ev, ["e"], "event_type", 64)


@query(_simple(r"SELECT role AS g, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS e FROM conversations", 256, "role"))
def turn_vocab(spark: SparkSession, d: str) -> DataFrame:
    words = load_table(spark, d, "conversations", ["role", "text"]).select("role", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("e"))
    return _counted(words, ["e"], "role", 256)


@query(_simple("SELECT lang AS g, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS e FROM (SELECT lang, ws, unnest(generate_series(1, len(ws) - 2)) AS i FROM (SELECT lang, string_split(text, ' ') AS ws FROM documents) WHERE len(ws) >= 3)", 2048, "lang"))
def word_ngrams(spark: SparkSession, d: str) -> DataFrame:
    made = shingles.ngram_levels(load_table(spark, d, "documents", ["lang", "text"]), "text", ["lang"], M, 3, SQL_HASH)
    return sets.estimate(made, ["lang"]).select("lang", F.round("tlc", 4).alias("estimate"))


@query(_simple("SELECT l_linestatus AS g, l_orderkey::VARCHAR AS e FROM lineitem WHERE l_quantity BETWEEN 10 AND 30 AND l_returnflag IN ('A', 'R') AND l_shipdate >= TIMESTAMP '1994-01-01'", 256, "l_linestatus"))
def filtered_sketch(spark: SparkSession, d: str) -> DataFrame:
    li = load_table(spark, d, "lineitem").filter(F.col("l_quantity").between(10, 30) & F.col("l_returnflag").isin("A", "R") & (F.col("l_shipdate") >= F.lit("1994-01-01").cast("timestamp_ntz")))
    return _counted(li.select("l_linestatus", "l_orderkey"), ["l_orderkey"], "l_linestatus", 256)


@query(_PACKED)
def store_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Packed sketches written by kind, and read back."""
    import uuid

    path = f"{shared_folder(spark)}/sketches-{uuid.uuid4().hex}"
    store.save_sketches(store.packed_sketches(bitmaps(spark, d, 256), ["g"], 256), path)
    return store.load_sketches(spark, path, "floor4").select("g", "floor", F.array_join(F.col("words").cast("array<string>"), ",").alias("words"))


def stored(spark: SparkSession, d: str) -> DataFrame:
    return udf.sketch_agg(stacked(spark, d), ["e"], ["g"], M, SQL_HASH, 60)


@query(oracles.base(floors=False) + ", a AS (SELECT g, x.reg, lvl FROM (SELECT DISTINCT g FROM s) q CROSS JOIN (SELECT unnest(generate_series(0, 2047)) AS reg) x LEFT JOIN s USING (g, reg)) SELECT g, count(lvl) AS filled, sum(coalesce(lvl, -1))::BIGINT AS levels FROM a GROUP BY g")
def udaf_sketch(spark: SparkSession, d: str) -> DataFrame:
    """Sketches made by the aggregate over groups, read byte by byte."""
    code = lambda i: F.conv(F.hex(F.substring("sketch", i, F.lit(1))), 16, 10).cast("int")
    values = F.transform(F.sequence(F.lit(5), F.lit(4 + M)), lambda i: F.when(code(i) > 127, -1).otherwise(code(i)))
    v = stored(spark, d).select("g", values.alias("v"))
    return v.select("g", F.size(F.filter("v", lambda x: x >= 0)).cast("bigint").alias("filled"), F.aggregate("v", F.lit(0).cast("bigint"), lambda s, x: s + x).alias("levels"))


@query(oracles.base() + "," + oracles.tlc(guard=False) + " SELECT g, round(tlc, 4) AS estimate FROM t")
def udf_estimate(spark: SparkSession, d: str) -> DataFrame:
    return stored(spark, d).select("g", F.round(udf.sketch_estimate("sketch"), 4).alias("estimate"))


@query(oracles.base() + " SELECT g, t AS tier, z, round(pow(2.0, t) * 2048 * ln(2048.0 / z), 4) AS estimate FROM z WHERE z > 0 AND z < 2048")
def udtf_tiers(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark)
    stored(spark, d).createOrReplaceTempView("floorcount_sketches")
    return spark.sql("SELECT g, tier, z, round(t.estimate, 4) AS estimate FROM floorcount_sketches, LATERAL sketch_tiers(sketch) t")


# --- order-dependent types, baselines, simulations: no SQL -----------------------------------------------------------


@query()
def spark_hllpp(spark: SparkSession, d: str) -> DataFrame:
    return sets.spark_hllpp(stacked(spark, d), "e", ["g"])


@query()
def lib_hll_sketch(spark: SparkSession, d: str) -> DataFrame:
    return sets.library_sketch(stacked(spark, d), "e", ["g"])


@query(f"SELECT g, count(DISTINCT e)::BIGINT AS estimate FROM ({oracles.STACKED}) GROUP BY g")
def lib_theta_sketch(spark: SparkSession, d: str) -> DataFrame:
    return sets.theta_sketch(stacked(spark, d), "e", ["g"])


_CAPPED = oracles.base("SELECT l_suppkey AS g, l_orderkey::VARCHAR AS e FROM lineitem", 64) + "," + oracles.tlc(64)


@query(_CAPPED + ", n AS (SELECT g, count(*) AS n FROM e GROUP BY g) SELECT t.g AS l_suppkey, round(least(tlc, n), 4) AS estimate FROM t JOIN n ON n.g = t.g")
def est_capped(spark: SparkSession, d: str) -> DataFrame:
    """Estimates that the rows added bound from above."""
    li = load_table(spark, d, "lineitem", ["l_suppkey", "l_orderkey"])
    rows = li.groupBy(F.col("l_suppkey").alias("_s")).agg(F.count(F.lit(1)).alias("n"))
    est = sets.estimate(levels.build_levels(li, ["l_orderkey"], ["l_suppkey"], 64, SQL_HASH), ["l_suppkey"], 64)
    return est.join(rows, F.col("l_suppkey") == F.col("_s")).select("l_suppkey", F.round(sets.capped(F.col("tlc"), F.col("n")), 4).alias("estimate"))


@query(oracles.base("SELECT user_id AS g, event_id::VARCHAR AS e FROM events", 256, floors=False) + ", u AS (SELECT g, count(DISTINCT place) AS seen, count(DISTINCT reg) AS n FROM l GROUP BY g) SELECT g AS user_id, seen::INT AS seen, seen >= 24 AS allocated, CASE WHEN seen >= 24 THEN n ELSE 0 END AS n_regs FROM u")
def lazy_users(spark: SparkSession, d: str) -> DataFrame:
    """Users' events: registers only for users whose small bitmap holds 24 places or more."""
    micro, regs = levels.build_lazy(load_table(spark, d, "events", ["user_id", "event_id"]), ["event_id"], ["user_id"], 256, 24, SQL_HASH)
    held = regs.groupBy(F.col("user_id").alias("_u")).agg(F.count(F.lit(1)).alias("n"))
    return micro.join(held, F.col("user_id").eqNullSafe(F.col("_u")), "left").select("user_id", F.bit_count("micro").alias("seen"), "allocated", F.coalesce("n", F.lit(0)).alias("n_regs"))


@query()
def update_share(spark: SparkSession, d: str) -> DataFrame:
    """Of rows added to one sketch, those that pass the exit test, and of these the share that changes a register."""
    made = state.sequential(load_table(spark, d, "lineitem", ["l_orderkey", "l_linenumber"]), ["l_orderkey", "l_linenumber"], lambda: state.FloorSketch(256))
    return made.agg(F.sum("rows").alias("rows"), F.sum("passed").alias("passed"), F.sum("updates").alias("updates"), F.sum("promotions").alias("promotions")).withColumn("share", F.col("updates") / F.col("passed"))


def _sequential(spec: str, kind: type = state.FloorSketch, tool: Callable = E.est_tlc):
    def run(spark: SparkSession, d: str) -> DataFrame:
        make = simulate.SEQUENTIAL[spec]
        parts = state.sequential(stacked(spark, d), ["e"], lambda: make(M), ["g"])
        return state.merge_sketches(parts, ["g"], kind).select("g", "rows", "floor", F.round(tool(F.col("cells"), M), 4).alias("estimate"))

    return run


for _s in ("floor4", "floor3", "fhist6"):
    add(f"sequential_{_s}", _sequential(_s))
add("offset4_trunc", _sequential("offset4_trunc", state.TruncatedOffset, E.est_hll))


@query()
def twobit(spark: SparkSession, d: str) -> DataFrame:
    """The two-bit family on simulated streams: its own estimates and errors."""
    own = simulate.simulate_types(spark, 4, M, [1000, 10_000, 100_000]).filter("spec = 'twobit'")
    return measures.by_checkpoint(measures.with_errors(own, "checkpoint", "own"))


@query()
def simulate_unique(spark: SparkSession, d: str) -> DataFrame:
    """All-distinct streams to 8,388,608 elements, at checkpoints a tenth apart; by the one-per-cent rule with points=simulate.checkpoints(1 << 23)."""
    rows = simulate.simulate_unique(spark, 16, M, simulate.checkpoints(1 << 23, 1.1))
    return measures.accuracy(rows, M, ["hll", "hybrid", "tlc", "tlc_layered", "hybrid_layered", "gra"])


_SKEWED = ("floor4", "floor3", "abs6")


def _skewed(rows: DataFrame) -> DataFrame:
    each = rows.select("spec", "checkpoint", "truth", F.explode(F.array(F.struct(F.lit(False).alias("repair"), "cells"), F.struct(F.lit(True).alias("repair"), F.col("repaired").alias("cells")))).alias("x"))
    # only three-bit registers have a repaired form of their own
    some = each.filter("spec = 'floor3' OR NOT x.repair")
    tools = F.explode(F.array(*[F.struct(F.lit(k).alias("method"), f(F.col("x.cells")).alias("estimate")) for k, f in (("tlc", lambda c: E.est_tlc(c, 256)), ("hybrid", lambda c: E.est_hybrid(c, 256)), ("hll", lambda c: E.est_hll(c, 256)))])).alias("y")
    est = some.select("spec", "checkpoint", "truth", "x.repair", tools).select("spec", "checkpoint", "truth", "repair", "y.method", "y.estimate").filter("(method = 'hll') = (spec = 'abs6')")
    return measures.by_checkpoint(measures.with_errors(est, "truth", "estimate"), ["spec", "repair", "method"])


@query()
def simulate_skewed(spark: SparkSession, d: str) -> DataFrame:
    """Customers of the orders, who come about ten times each: absolute, four- and three-bit registers, repaired and not; the last row is the streams' end."""
    customers = load_table(spark, d, "orders", ["o_custkey", "o_orderkey"])
    return _skewed(simulate.repeated(customers, 16, _SKEWED, 256, [300, 1000, 3000, 10_000, 20_000, 30_000, 40_000]))


@query()
def skewed_divergence(spark: SparkSession, d: str) -> DataFrame:
    """Three against four bits far past the point where repair and promotions by duplicates meet: up to 1,000 elements a register."""
    return _skewed(simulate.simulate_skewed(spark, 8, _SKEWED, 256, 360_000, 4, [8_000, 32_000, 64_000, 128_000, 256_000], at_end=True))


@query()
def merge_study(spark: SparkSession, d: str) -> DataFrame:
    """The order keys dealt to 1 to 64 sketches: four bits, which lose little, and three, which show the loss that grows with the parts."""
    rows = simulate.merge_dealt(order_keys(spark, d), 8, 256, widths=(4, 3))
    est = rows.select("width", "parts", "truth", "clamped", "lost", E.est_hybrid(F.col("cells"), 256).alias("estimate"))
    return measures.with_errors(est, "truth", "estimate").groupBy("width", "parts").agg(F.avg("signed").alias("bias"), F.avg("absolute").alias("mae"), F.avg("clamped").alias("clamped"), F.avg("lost").alias("lost"))


@query()
def merge_shingles(spark: SparkSession, d: str) -> DataFrame:
    """Shingles of the documents dealt to 1, 8, 16 and 64 four-bit sketches, encoded, merged by the larger register, and estimated; the bitmaps lose nothing."""
    docs = load_table(spark, d, "documents", ["doc_id", "text"]).select(F.pmod(F.xxhash64("doc_id"), F.lit(64)).cast("int").alias("part"), "text")
    fine = shingles.shingle_levels(docs, "text", ["part"], 256)
    whole = sets.estimate(levels.merge_levels(fine), (), 256).select(F.col("tlc").alias("lossless"))
    out = []
    for k in (1, 8, 16, 64):
        dealt = levels.merge_levels(fine.withColumn("part", F.col("part") % k), by=["part"])
        packed = encode.pack(encode.to_floor(dealt, ["part"], 256), ["part"], 256)
        regs = encode.unpack(encode.merge_packed(packed.select("floor", "words"), (), 256), (), 256).select("reg", (F.col("offset") + F.col("floor")).alias("lvl"))
        bits = regs.filter("lvl >= 0").select("reg", F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("lvl").cast("int")).alias("bits"))
        out.append(sets.estimate(bits, (), 256).select(F.lit(k).alias("parts"), F.col("tlc").alias("merged")))
    every = reduce(DataFrame.unionAll, out).crossJoin(F.broadcast(whole))  # one row
    return every.select("parts", F.round("merged", 4).alias("merged"), F.round("lossless", 4).alias("lossless"), F.round(F.col("merged") / F.col("lossless") - 1, 6).alias("undercount"))


#: The rows of the equal-memory comparison: registers, type, estimate.
GRID = (
    (1024, "hist8", "gra"), (2048, "hist8", "gra"), (2048, "floor4", "hybrid"), (2048, "fhist5", "tlc_layered_h1"), (2048, "fhist6", "tlc_layered"), (2048, "fhist7", "tlc_layered_h3"),
    (2048, "fhist6", "hybrid_layered"), (2560, "floor4", "hybrid"), (3072, "floor4", "hybrid"), (3584, "floor4", "hybrid"), (4096, "floor4", "hybrid"),
)


@query()
def memory_grid(spark: SparkSession, d: str) -> DataFrame:
    """Errors over the growing order keys at sizes of equal and unequal memory, with bytes: history bits against more registers."""
    points = [2000, 5000, 10_000, 20_000, 50_000, 100_000, 200_000, 500_000]
    out = []
    for m in sorted({m for m, _, _ in GRID}):
        rows = simulate.grown(order_keys(spark, d), 64, m, points)
        for _, spec, method in (g for g in GRID if g[0] == m):
            curve = measures.accuracy(rows, m, [method])
            out.append(measures.weighted(curve).select(F.lit(spec).alias("spec"), F.lit(m).alias("m"), F.lit(method).alias("method"), F.lit(measures.packed_bytes(spec, m)).alias("bytes"), "peak", "by_log", "by_width"))
    return reduce(DataFrame.unionAll, out)


@query()
def memory_variance(spark: SparkSession, d: str) -> DataFrame:
    """Bits held times variance over the order keys, of absolute registers with history and of four-bit ones, at one size."""
    rows = simulate.grown(order_keys(spark, d), 32, M, [50_000, 200_000])
    parts = [measures.memory_variance(measures.accuracy(rows, M, [k]), spec, M).withColumn("spec", F.lit(spec)) for spec, k in (("abs6", "hll"), ("floor4", "hybrid"), ("hist8", "gra"), ("fhist6", "hybrid_layered"))]
    return measures.relative_to(reduce(DataFrame.unionAll, parts).groupBy("spec").agg(F.avg("mvp").alias("mvp")), "spec", "abs6", "mvp")


@query()
def history_ablation(spark: SparkSession, d: str) -> DataFrame:
    """The layered count and the corrected mean of the growing order keys with none to three history bits, and remaining area with two."""
    rows = simulate.grown(order_keys(spark, d), 64, M, [5_000, 20_000, 60_000, 200_000])
    tools = {"layered_h0": lambda c: E.est_tlc(c, M), **{f"layered_h{h}": (lambda c, h=h: E.est_tlc_layered(c, M, h)) for h in (1, 2, 3)}, **{f"mean_h{h}": (lambda c, h=h: E.est_mean_hist(c, M, h)) for h in (0, 1, 2, 3)}, "gra": lambda c: E.est_gra(c, M)}
    each = F.explode(F.array(*[F.struct(F.lit(k).alias("method"), f(F.col("cells")).alias("estimate")) for k, f in tools.items()])).alias("x")
    return measures.by_checkpoint(measures.with_errors(rows.select("checkpoint", each).select("checkpoint", "x.*"), "checkpoint", "estimate"), ["method"])


@query()
def bias_curves(spark: SparkSession, d: str) -> DataFrame:
    """Signed errors of tiers, of history alone and of their blend along the last two octaves of the order keys: the first two lean opposite ways in turn."""
    points = [round(60_000 * 2 ** (i / 8)) for i in range(17)]
    curve = measures.accuracy(simulate.grown(order_keys(spark, d), 96, M, points), M, ["tlc", "hist_lc", "tlc_layered"])
    return curve.groupBy("checkpoint").pivot("method", ["tlc", "hist_lc", "tlc_layered"]).agg(F.first("bias").alias("bias"), F.first("mae").alias("mae"))


@query()
def averaging_comparison(spark: SparkSession, d: str) -> DataFrame:
    """The three means of the growing order keys, each corrected by its own table, and without correction."""
    rows = simulate.grown(order_keys(spark, d), 64, M, [1000, 2048, 8000, 100_000])
    tools = {"occ_mean": E.est_occ_mean, "harm_mean": E.est_harm_mean, "geo_mean": E.est_geo_mean}
    structs = [F.struct(F.lit(k).alias("method"), F.lit(cf).alias("corrected"), (E.corrected(f(F.col("cells"), M), M, k) if cf else f(F.col("cells"), M)).alias("estimate")) for k, f in tools.items() for cf in (True, False)]
    est = rows.select("checkpoint", F.explode(F.array(*structs)).alias("x")).select("checkpoint", "x.*")
    return measures.by_checkpoint(measures.with_errors(est, "checkpoint", "estimate"), ["method", "corrected"])


@query()
def cf_curve(spark: SparkSession, d: str) -> DataFrame:
    """Correction factors measured on the growing order keys beside the analytic ones."""
    cf = simulate.build_cf(simulate.grown(order_keys(spark, d), 32, M, [500, 2000, 5000, 20_000, 100_000]), M, E.est_occ_mean)
    return cf.select("checkpoint", "raw", "factor", (E.corrected(F.col("raw"), M) / F.col("raw")).alias("analytic"))


@query()
def type_comparison(spark: SparkSession, d: str) -> DataFrame:
    """Every sketch type on the same simulated streams, each with its estimator."""
    rows = simulate.simulate_types(spark, 4, M, [1000, 10_000, 100_000])
    c = F.col("cells")
    pick = {"floor4": E.est_hybrid(c, M), "floor3": E.est_hybrid(c, M), "floor5": E.est_hybrid(c, M), "fhist5": E.est_tlc_layered(c, M, 1), "fhist6": E.est_hybrid_layered(c, M), "fhist7": E.est_tlc_layered(c, M, 3), "offset4_map": E.est_hll(c, M), "offset3_map": E.est_hll(c, M), "abs6": E.est_hll(c, M), "hist8": E.est_gra(c, M), "offset4_trunc": E.est_hll(c, M)}
    est = F.col("own")
    for k, e in pick.items():
        est = F.when(F.col("spec") == k, e).otherwise(est)
    return measures.by_checkpoint(measures.with_errors(rows.withColumn("estimate", est), "checkpoint", "estimate"), ["spec"])


@query()
def idempotence(spark: SparkSession, d: str) -> DataFrame:
    """Events added once, and each batch three times over: which sketches are unchanged, in every part of the rows."""

    def run(batches):
        import numpy as np
        import pandas as pd

        held = {k: (make(256), make(256)) for k, make in simulate.SEQUENTIAL.items()}
        for b in batches:
            h = b["h"].to_numpy().astype(np.int64).view(np.uint64)
            for once, thrice in held.values():
                once.add_batch(h)
                for _ in range(3):
                    thrice.add_batch(h)
        for k, (once, thrice) in held.items():
            yield pd.DataFrame({"spec": [k], "unchanged": [bool((once.levels() == thrice.levels()).all())], "lower": [int((once.levels() < thrice.levels()).sum())], "floor_risen": [thrice.floor - once.floor]})

    rows = levels.hashed(load_table(spark, d, "events", ["event_id"]), ["event_id"])
    made = rows.mapInPandas(run, "spec string, unchanged boolean, lower int, floor_risen int")
    return made.groupBy("spec").agg(F.bool_and("unchanged").alias("unchanged"), F.sum("lower").alias("lower"), F.max("floor_risen").alias("floor_risen"))


@query()
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    """Users of every closed hour, from the events read as a stream into Parquet."""
    import uuid

    from floorcount.sources.tables import stream_table
    from floorcount.streaming.distinct import windowed_estimates, write_estimates

    root = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    load_table(spark, d, "events").withColumn("day", F.to_date("ts")).write.partitionBy("day").parquet(f"{root}/in")
    events = stream_table(spark, f"{root}/in", spark.read.parquet(f"{root}/in").schema, files=1000)
    write_estimates(windowed_estimates(events, ["user_id"], 64, kind=SQL_HASH), f"{root}/out", f"{root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("start timestamp, end timestamp, estimate double").parquet(f"{root}/out")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
