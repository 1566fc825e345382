"""Quality rules with thresholds that follow each language and source.

Three steps. Each text is measured once. The measures of the documents that pass the fixed base rule are gathered for each
language and source in quantile sketches: counts over buckets that keep seven leading bits of a value, so two sketches
merge by adding counts, in any order and without loss, and a sketch has a fixed number of buckets whatever it holds. An
upper fence is read from each sketch, joined to the documents, and those beyond a fence of their own group are rejected.

A group's sketch is blended with its language's, which weighs as much as PRIOR documents, and the language's with that of
all, so there is no size at which a group turns from one threshold to another. Ratios that most clean documents have
nothing of (repeated lines and windows) are sketched over the documents that have some.

Junk must not set its own threshold: no fence exceeds that which half of the groups of its language stay within, each group
counting once whatever it holds. A language of fewer than BOUND_GROUPS groups is bounded by the groups of all.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from floorcount.llm.scratch import Scratch, free_name, must_be_free, tidy

WHITE = b" \t\n\x0b\x0c\r"
SYMBOLS = b"#*$%&|<>"
#: Bytes that start no code point.
REST = bytes(range(0x80, 0xC0))
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")
REPEAT_WINDOW = 8
#: Base rule: at least so many words, at most so many of 100 words in repeated windows.
BASE_WORDS, BASE_REPEAT = 20, 30

#: What the fences look at, in thousandths: name, numerator, denominator.
RATIOS = (("symbols", "n_symbols", "word_chars"), ("dup_lines", "n_dup_lines", "n_lines"), ("repeats", "n_repeat_words", "n_words"), ("word_length", "word_chars", "n_words"))
#: A value is beyond the fence if it exceeds q90 + SPREAD * (q90 - q50), in buckets.
LOW_Q, HIGH_Q, SPREAD = 50, 90, 4
#: Ratios that are sketched over the documents that have some.
OF_SOME = ("dup_lines", "repeats")
#: Thousandths that are rejected nowhere: one symbol in a hundred characters. Other ratios have no such value.
TOLERANCE = {"symbols": 10}
#: Documents that a language's sketch weighs in each of its groups, and that of all in each language; ONE is a document's weight.
PRIOR, PRIOR_ALL, ONE = 30, 10, 1_000_000
#: Groups of a language from which on they bound its fences.
BOUND_GROUPS = 3
#: Fences, of at most 300 bytes each, up to which they are sent to every executor.
FEW_GROUPS = 50_000


def repeated_words(words: list[bytes], span: int = REPEAT_WINDOW) -> int:
    """Words covered by windows of span words that stand in the text twice or more."""
    n = len(words) - span + 1
    if n < 2:
        return 0
    ids: dict[bytes, int] = {}
    key = np.fromiter((ids.setdefault(w, len(ids)) for w in words), dtype=np.int64, count=len(words))
    width = 1
    while width < span:  # windows of twice the width, numbered anew by their two halves
        pair = key[: len(key) - width] * (int(key.max()) + 1) + key[width:]
        if 2 * width == span:
            break
        key = np.unique(pair, return_inverse=True)[1]
        width *= 2
    _, where, count = np.unique(pair, return_inverse=True, return_counts=True)
    starts = np.flatnonzero(count[where] > 1)
    if not len(starts):
        return 0
    edge = np.zeros(len(words) + 1, dtype=np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + span, -1)
    return int(np.count_nonzero(np.cumsum(edge)))


def may_repeat(words: list[bytes]) -> bool:
    """False only if no window of two words stands twice."""
    return len(set(zip(words, words[1:]))) < len(words) - 1


def measure_text(text: bytes | None) -> tuple[int, ...]:
    text = text or b""
    words = text.split()
    lines = [x for x in text.split(b"\n") if x and not x.isspace()] if words else []
    return (
        len(words),
        len(text.translate(None, WHITE + REST)),
        len(text) - len(text.translate(None, SYMBOLS)),
        len(lines) - len(set(lines)),
        repeated_words(words) if may_repeat(words) else 0,
        len(lines),
    )


def with_measures(df: DataFrame, text: str = "text", keep_text: bool = False) -> DataFrame:
    """The columns of df, the text only if asked for, and a struct `measures` of the base counts; null texts have none of anything."""
    rest = [f for f in df.schema.fields if keep_text or f.name != text]
    kind = T.StructType([T.StructField(m, T.LongType()) for m in MEASURES])
    schema = T.StructType([*rest, T.StructField("measures", kind)])
    at = [f.name for f in rest].index(text) if keep_text else len(rest)
    given = df if keep_text else df.select(*[F.col(f"`{f.name}`") for f in rest], F.col(f"`{text}`").cast("string"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [measure_text(x) for x in batch.column(at).cast(pa.binary()).to_pylist()]
            counts = [pa.array([r[i] for r in rows], pa.int64()) for i in range(len(MEASURES))]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(rest)], pa.StructArray.from_arrays(counts, names=list(MEASURES))], names=schema.names)

    return given.mapInArrow(tidy(run), schema)


def bucket(value: Column) -> Column:
    """The bucket of a whole number from 0: the number itself below 256, else its seven bits after the leading one."""
    shift = F.length(F.bin(value)) - 8
    return F.when(value < 256, value).otherwise(shift * 128 + F.call_function("shiftright", value, F.greatest(shift, F.lit(0)))).cast("long")


def _bucket(value: int) -> int:
    shift = max(0, value.bit_length() - 8)
    return value if value < 256 else shift * 128 + (value >> shift)


def base_failed(m: str = "measures") -> Column:
    return (F.col(f"{m}.n_words") < BASE_WORDS) | (F.col(f"{m}.n_repeat_words") * 100 > F.col(f"{m}.n_words") * BASE_REPEAT)


def ratio(num: str, den: str, m: str = "measures") -> Column:
    """Thousandths, rounded down; 0 over nothing."""
    d = F.col(f"{m}.{den}")
    return F.when(d > 0, F.floor(F.col(f"{m}.{num}") * 1000 / F.when(d > 0, d))).otherwise(0).cast("long")


def sketches(measured: DataFrame, by: tuple[str, str] = ("lang", "source")) -> DataFrame:
    """Rows (lang, source, ratio, bucket, docs): mergeable by summing docs. Documents failing the base rule are left out."""
    each = F.explode(F.array(*[F.struct(F.lit(name).alias("ratio"), bucket(ratio(a, b)).alias("bucket")) for name, a, b in RATIOS]))
    return (
        measured.filter(~base_failed())
        .select(*[F.col(f"`{c}`").alias(k) for c, k in zip(by, ("g_lang", "g_source"))], each.alias("x"))
        .filter((F.col("x.bucket") > 0) | ~F.col("x.ratio").isin(*OF_SOME))
        .groupBy("g_lang", "g_source", F.col("x.ratio").alias("ratio"), F.col("x.bucket").alias("bucket"))
        .agg(F.count(F.lit(1)).alias("docs"))
    )


def _weighed(rows: DataFrame, by: list[str], most: int) -> DataFrame:
    """rows (by..., bucket, weight) with `share`: the weight's part of `most` documents, whole numbers, so sums are exact in any order."""
    total = rows.groupBy(*[F.col(c).alias(f"_{c}") for c in by]).agg(F.sum("weight").alias("total"))
    same = reduce(lambda x, c: x & F.col(c).eqNullSafe(F.col(f"_{c}")), by, F.lit(True))
    part = F.floor(F.lit(float(most * ONE)) * (F.col("weight") / F.col("total"))).cast("bigint").alias("share")
    return rows.join(total, same).select(*by, "bucket", part)


def blended(sketch: DataFrame, scratch: Scratch) -> DataFrame:
    """Rows (g_lang, g_source, ratio, bucket, weight): each group's own counts and its part of its language's and of all."""
    own = sketch.select("g_lang", "g_source", "ratio", "bucket", (F.col("docs") * ONE).alias("weight"))
    every = _weighed(own.groupBy("ratio", "bucket").agg(F.sum("weight").alias("weight")), ["ratio"], PRIOR_ALL)
    langs = sketch.select("g_lang").distinct()
    ratios = F.explode(F.array(*[F.lit(name) for name, _, _ in RATIOS]))
    to_lang = langs.select("g_lang", ratios.alias("r")).join(every, F.col("r") == F.col("ratio")).select("g_lang", "ratio", "bucket", F.col("share").alias("weight"))
    of_lang = scratch.keep(own.select("g_lang", "ratio", "bucket", "weight").unionAll(to_lang).groupBy("g_lang", "ratio", "bucket").agg(F.sum("weight").alias("weight")), "languages")
    lang = _weighed(of_lang, ["g_lang", "ratio"], PRIOR).withColumnRenamed("g_lang", "_l")
    to_group = sketch.select("g_lang", "g_source").distinct().join(lang, F.col("g_lang").eqNullSafe(F.col("_l"))).select("g_lang", "g_source", "ratio", "bucket", F.col("share").alias("weight"))
    return own.unionAll(to_group).groupBy("g_lang", "g_source", "ratio", "bucket").agg(F.sum("weight").alias("weight"))


def fences(sketch: DataFrame, scratch: Scratch) -> DataFrame:
    """Rows (g_lang, g_source, fences): the fences as a map of ratio to bucket.

    What is read several times, sketches and rows of one group and ratio, is written first: as one plan it was repeated in
    all that reads it, and the driver holds a plan's text anew after each of its stages.
    """
    sketch = scratch.keep(sketch, "sketches")
    key = ["g_lang", "g_source", "ratio"]
    ordered = blended(sketch, scratch).withColumn("upto", F.sum("weight").over(W.partitionBy(*key).orderBy("bucket"))).withColumn("total", F.sum("weight").over(W.partitionBy(*key)))
    at = lambda q: F.min(F.when(F.col("upto") * 100 >= F.col("total") * q, F.col("bucket")))
    own = ordered.groupBy(*key).agg(at(LOW_Q).alias("low"), at(HIGH_Q).alias("high")).withColumn("raw", F.col("high") + SPREAD * (F.col("high") - F.col("low")))
    own = scratch.keep(own, "own-fences")
    # each group counts once, so a source is one voice whatever its share of the rows
    middle = F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY raw)").cast("long")
    of_all = own.groupBy(F.col("ratio").alias("r0")).agg(middle.alias("all_half"))
    of_lang = own.groupBy(F.col("g_lang").alias("b_lang"), F.col("ratio").alias("r1")).agg(middle.alias("half"), F.count(F.lit(1)).alias("n")).filter(F.col("n") >= BOUND_GROUPS)
    bound = own.join(F.broadcast(of_all), F.col("ratio") == F.col("r0")).join(of_lang, F.col("g_lang").eqNullSafe(F.col("b_lang")) & (F.col("ratio") == F.col("r1")), "left")
    fence = F.least(F.col("raw"), F.coalesce("half", "all_half"))
    return bound.groupBy("g_lang", "g_source").agg(F.map_from_entries(F.collect_list(F.struct("ratio", fence.alias("fence")))).alias("fences"))


def judge(df: DataFrame, text: str = "text", lang: str = "lang", source: str = "source", scratch: Scratch | None = None, keep_text: bool = False) -> DataFrame:
    """The columns of df, the text only if asked for, with `measures`, `base_failed`, `beyond` (array of ratio names) and `kept`.

    Null languages and sources are groups of their own. Null and empty texts have no words and fail the base rule; repeated
    rows each count and are judged alike; an empty table gives an empty one. Names that the result adds must be free.
    Without the text, the measures are written once; with it, they are taken twice rather than write all texts.
    """
    must_be_free(df, "measures", "base_failed", "beyond", "kept")
    scratch = scratch or Scratch(df.sparkSession, "quality")
    measured = with_measures(df, text, keep_text)
    if keep_text:
        counted = with_measures(df.select(f"`{text}`", f"`{lang}`", f"`{source}`"), text)
    else:
        measured = counted = scratch.keep(measured, "measures")
    found = scratch.keep(fences(sketches(counted, (lang, source)), scratch), "fences")
    # a row for each language and source: sent to every executor only if there are few
    send = F.broadcast if found.count() <= FEW_GROUPS else (lambda x: x)
    key = lambda c: F.coalesce(F.concat(F.lit("="), F.col(c)), F.lit("-"))
    free = lambda n: free_name(measured, n)
    c = {n: F.col(free(f"_{n}")) for n in ("l", "s", "l2", "s2", "f2")}
    keyed = measured.withColumns({free("_l"): key(f"`{lang}`"), free("_s"): key(f"`{source}`")})
    own = send(found.select(key("g_lang").alias(free("_l2")), key("g_source").alias(free("_s2")), F.col("fences").alias(free("_f2"))))
    joined = keyed.join(own, (c["l"] == c["l2"]) & (c["s"] == c["s2"]), "left")
    limit = lambda name: F.greatest(F.try_element_at(c["f2"], F.lit(name)), F.lit(TOLERANCE.get(name, 0)).cast("long"))
    beyond = F.array_compact(F.array(*[F.when(F.try_element_at(c["f2"], F.lit(name)).isNotNull() & (bucket(ratio(a, b)) > limit(name)), F.lit(name)) for name, a, b in RATIOS]))
    out = [F.col(f"`{c}`") for c in measured.columns]
    judged = joined.select(*out, base_failed().alias("base_failed"), F.when(base_failed(), F.array().cast("array<string>")).otherwise(beyond).alias("beyond"))
    return judged.withColumn("kept", ~F.col("base_failed") & (F.size("beyond") == 0))
