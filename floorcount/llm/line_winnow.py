"""Line dedup by winnowing, in DataFrame operations only.

A run is a stretch of lines that follow each other, lines without words left out of account, and holds RUN_WORDS words or more.
A line goes if it lies in a run that stands earlier, at any place; nothing else goes.

Lines with words are hashed. Grams are the fewest lines from a line on that hold GRAM_WORDS words. Of the grams that start
within RUN_WORDS - GRAM_WORDS words of a line the smallest hash is selected, so every run has a selected gram, the same one
wherever it stands, and documents without a gram that is selected elsewhere too have no repeated run. In the others each
match is extended both ways to its ends: from each line on, the fewest lines that hold RUN_WORDS words form a window, and so
do the fewest that hold as many up to each line. Each line of a run lies in such a window inside the run. A window is known
by the hash of its line hashes and held against the earliest place of the same window, whatever the number of documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from floorcount.llm.scratch import Bucketed, Scratch, free_name, must_be_free

GRAM_WORDS, RUN_WORDS = 12, 25
WORD = r"[^\x20\x09-\x0D]+"


def line_hashes(df: DataFrame, doc: str, text: str) -> DataFrame:
    """Rows (key, d, k, line, h, words, before): hash, words, and words of the text before it, of each line with a word.

    key stands for doc_id and text, of which k is the hash."""
    body = F.col(f"`{text}`").cast("string")
    texts = df.select(F.col(f"`{doc}`").alias("d"), F.unhex(F.md5(body)).alias("k"), F.split(body, "\n", -1).alias("lines"))
    key = F.unhex(F.md5(F.concat(F.coalesce(F.concat(F.lit("="), F.col("d").cast("string")), F.lit("-")), F.lit(" "), F.hex("k"))))
    lines = texts.select(key.alias("key"), "d", "k", F.posexplode("lines").alias("line", "t"))
    counted = lines.select("key", "d", "k", "line", F.unhex(F.md5("t")).alias("h"), F.regexp_count("t", F.lit(WORD)).cast("long").alias("words")).filter("words > 0")
    # rows repeated as they are count as one document; one exchange serves this, the windows and the written table
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    once = counted.repartition(parts, "key").dropDuplicates(["key", "line"])
    return once.withColumn("before", F.sum("words").over(W.partitionBy("key").orderBy("line")) - F.col("words"))


def joined(hashes: Column) -> Column:
    return F.unhex(F.md5(F.array_join(hashes, "")))


def fingerprints(lines: DataFrame) -> DataFrame:
    """Rows (key, d, k, line, gram, ahead, last, back, first).

    gram, from `line` on, is null unless selected. ahead is the window of lines from `line` to `last`, back that of `first` to
    `line`; a window is null where the text holds too few words, and back where its lines are an ahead of `first` already.
    """
    doc = W.partitionBy("key")
    by, ending = doc.orderBy("before"), doc.orderBy("upto")
    known = lines.withColumns({"x": F.lower(F.hex("h")), "upto": F.col("before") + F.col("words"), "total": F.sum("words").over(doc)})
    upto = ending.rangeBetween(1 - RUN_WORDS, W.currentRow)
    back = known.withColumns({"b": F.collect_list("x").over(upto), "start": F.min(F.struct("before", "line")).over(upto)})
    own = (F.col("upto") >= RUN_WORDS) & (F.col("before") - F.col("start.before") >= RUN_WORDS)
    known = back.withColumns({"back": F.when(own, joined(F.col("b"))), "first": F.when(own, F.col("start.line"))}).drop("b", "start")
    left = F.col("total") - F.col("before")
    reach = by.rangeBetween(W.currentRow, RUN_WORDS - 1)
    grams = known.select(
        "key", "d", "k", "line", "before", "back", "first",
        F.when(left >= GRAM_WORDS, joined(F.collect_list("x").over(by.rangeBetween(W.currentRow, GRAM_WORDS - 1)))).alias("gram"),
        F.when(left >= RUN_WORDS, joined(F.collect_list("x").over(reach))).alias("ahead"),
        F.when(left >= RUN_WORDS, F.max("line").over(reach)).alias("last"),
    )
    apart = RUN_WORDS - GRAM_WORDS
    least = F.min(F.when(F.col("gram").isNotNull(), F.struct("gram", "before"))).over(by.rangeBetween(W.currentRow, apart))
    chosen = grams.withColumn("at", least["before"]).withColumn("chosen", F.collect_set("at").over(by.rangeBetween(-apart, W.currentRow)))
    selected = F.col("gram").isNotNull() & F.array_contains("chosen", F.col("before"))
    return chosen.select("key", "d", "k", "line", F.when(selected, F.col("gram")).alias("gram"), "ahead", "last", "back", "first")


def place() -> Column:
    """Order of places: doc_id with null last, text hash, line."""
    return F.struct(F.col("d").isNull().alias("none"), F.col("d").alias("d"), F.col("k").alias("k"), F.col("line").alias("line"))


def sharing(prints: DataFrame) -> DataFrame:
    """The keys of documents with a selected gram that is selected at another place too."""
    grams = prints.filter("gram is not null").select("gram", "key")
    shared = grams.groupBy(F.col("gram").alias("g")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("g")
    return grams.join(shared, F.col("gram") == F.col("g"), "left_semi").select("key").distinct()


def repeated_windows(prints: DataFrame) -> DataFrame:
    """Rows (d, k, first, last): the windows of RUN_WORDS words that stand earlier already."""
    both = F.explode(F.array(F.struct(F.col("ahead").alias("w"), F.col("line").alias("first"), "last"), F.struct(F.col("back").alias("w"), "first", F.col("line").alias("last"))))
    windows = prints.select("d", "k", both.alias("x")).select("x.w", "d", "k", F.col("x.first").alias("line"), "x.last").filter("w is not null")
    first = windows.groupBy(F.col("w").alias("g")).agg(F.min(place()).alias("p"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("g", "p")
    return windows.join(first.hint("merge"), F.col("w") == F.col("g")).filter(place() != F.col("p")).select("d", "k", F.col("line").alias("first"), "last")


def repeated_runs(windows: DataFrame) -> DataFrame:
    """Rows (d, k, first, last): stretches of lines that stand earlier already; disjoint."""
    runs = windows.distinct()
    order = W.partitionBy("d", "k").orderBy("first", "last")
    reach = F.max("last").over(order.rowsBetween(W.unboundedPreceding, -1))
    fresh = runs.withColumn("new", F.coalesce((F.col("first") > reach + 1).cast("int"), F.lit(1)))
    island = fresh.withColumn("island", F.sum("new").over(order.rowsBetween(W.unboundedPreceding, W.currentRow)))
    return island.groupBy("d", "k", "island").agg(F.min("first").alias("first"), F.max("last").alias("last")).drop("island")


def bridged(runs: Column, lines: Column) -> Column:
    """runs, in order, where those with only lines without words between them are one."""
    worded = lambda t: F.regexp_like(t, F.lit(WORD))
    bare = lambda a, b: ~F.exists(F.slice(lines, a["last"] + 2, b["first"] - a["last"] - 1), worded)

    def step(seen: Column, x: Column) -> Column:
        end = F.element_at(seen, -1)
        longer = F.concat(F.slice(seen, 1, F.size(seen) - 1), F.array(F.struct(end["first"].alias("first"), x["last"].alias("last"))))
        return F.when(bare(end, x), longer).otherwise(F.concat(seen, F.array(x)))

    return F.aggregate(F.slice(runs, 2, F.size(runs) - 1), F.slice(runs, 1, 1), step)


def dedup_lines(df: DataFrame, doc: str = "doc_id", text: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """df with the lines of later repeated runs taken out of `text`, and array `removed` of (first, last) line numbers.

    A run of RUN_WORDS words or more that stands earlier goes whole, wherever it stands; shorter ones stay.
    Lines are parted by \\n alone and numbered from 0; lines without words go where the lines with words before and after them go. Null texts stay
    null; empty ones stay empty; a text that loses every line becomes empty. Earlier means a smaller doc_id (null last), then
    text hash, then line. Rows with equal doc_id and text are one document and treated alike. An empty table gives an
    empty one. A column named `removed` must not be there.
    """
    must_be_free(df, "removed")
    scratch = scratch or Scratch(df.sparkSession, "lines")
    dealt = Bucketed(scratch, "fingerprints", "key")
    try:
        prints = dealt.keep(fingerprints(line_hashes(df, doc, text)))
        near = prints.join(sharing(prints).withColumnRenamed("key", "s"), F.col("key") == F.col("s"), "left_semi")
        found = scratch.keep(repeated_runs(repeated_windows(near)), "runs")
    finally:
        dealt.drop()
    runs = found.groupBy("d", "k").agg(F.array_sort(F.collect_list(F.struct("first", "last"))).alias("removed"))
    body = F.col(f"`{text}`").cast("string")
    at, d, k, run = (free_name(df, n) for n in ("_hash", "_doc", "_key", "_runs"))
    # texts are dealt by key at every size, whatever few runs a small table has
    runs = runs.select(F.col("d").alias(d), F.col("k").alias(k), F.col("removed").alias(run)).hint("merge")
    joined = df.withColumn(at, F.unhex(F.md5(body))).join(runs, F.col(f"`{doc}`").eqNullSafe(F.col(d)) & (F.col(at) == F.col(k)), "left")
    lines = F.split(body, "\n", -1)
    joined = joined.withColumn(run, F.when(F.size(run) > 1, bridged(F.col(run), lines)).otherwise(F.col(run)))
    removed = F.coalesce(run, F.array().cast(T.ArrayType(T.StructType([T.StructField("first", T.IntegerType()), T.StructField("last", T.IntegerType())]))))
    gaps = F.zip_with(F.concat(F.array(F.lit(-1)), F.transform(run, lambda x: x["last"])), F.concat(F.transform(run, lambda x: x["first"]), F.array(F.size(lines))), lambda a, b: F.slice(lines, a + 2, b - a - 1))
    kept = F.when(F.size(run) > 0, F.array_join(F.flatten(gaps), "\n")).otherwise(body)
    return joined.select(*[kept.alias(c) if c == text else F.col(f"`{c}`") for c in df.columns], removed.alias("removed"))
