"""Token totals by source, language and tokenizer version, kept up to date by signed deltas.

A batch of changes (insert, delete, revise) is turned into signed rows against the ledger of what each document counts
for now: an insert adds, a delete takes away what is there, a revision does both. The batch's rows are summed by the
rollup's key and written as one delta; totals are the sum of committed deltas.

The ledger is dealt into PARTS by a hash of doc_id; a batch reads the parts that it touches. A batch has an id: what it wrote
is complete once its marker is there, a batch that is complete is not applied again, and one that broke off leaves nothing
that is read. Each attempt writes to a folder of its own, which the marker names; should two attempts of one batch end,
the one first by name counts, for every reader. compact() folds the history into one row a document.
"""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

WORD = r"[^\x20\x09-\x0D]+"
#: Tokenizer versions that count in the JVM; others pass their counts in.
COUNTERS = {
    "words-1": lambda text: F.regexp_count(text, F.lit(WORD)),
    "words-2": lambda text: F.regexp_count(text, F.lit(r"[A-Za-z0-9\x{80}-\x{10FFFF}]+|[!-/:-@\[-`{-~]")),
}
KEY = ("source", "lang", "tokenizer")
#: Parts of the ledger, by hash of doc_id.
PARTS = 16
LEDGER = "part int, doc_id long, source string, lang string, tokenizer string, docs long, tokens long"
TOTALS = "source string, lang string, tokenizer string, docs long, tokens long"


def counted(df: DataFrame, tokenizer: str, text: str = "text") -> Column:
    """Tokens of a text by a version of COUNTERS; of null, 0."""
    return F.coalesce(COUNTERS[tokenizer](F.col(f"`{text}`").cast("string")), F.lit(0)).cast("long")


class Rollup:
    """Totals under a folder that all executors share.

    A document is known by doc_id and tokenizer. Rows with a null id are documents of their own, which nothing revises or
    deletes: each insert and revision adds. Of several changes to one document in a batch, the one with the largest seq
    counts, a delete before others of the same seq, then the larger count. Deletes and revisions of what isn't there take
    nothing away; a revision adds like an insert, and an insert of what is there revises. Null sources and languages are
    groups. An empty batch is committed and changes nothing; other columns of the changes are ignored.
    """

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def _path(self, *parts: str) -> str:
        return "/".join((self.folder, *parts))

    def _fs(self, path: str):
        p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return p, p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def _marks(self, kind: str) -> dict[str, str]:
        """The attempt of each name that counts, as the marker files tell."""
        path, fs = self._fs(self._path(kind))
        found = sorted(x.getPath().getName() for x in fs.listStatus(path)) if fs.exists(path) else []
        return {name: attempt for name, _, attempt in (x.rpartition("@") for x in reversed(found))}

    def _mark(self, kind: str, name: str, attempt: str) -> None:
        path, fs = self._fs(self._path(kind, f"{name}@{attempt}"))
        fs.create(path, False).close()

    def committed(self) -> list[str]:
        """Ids of complete batches; one marker file for each attempt that ended."""
        return sorted(self._marks("commits"))

    def _read(self, kind: str, schema: str) -> DataFrame:
        """The rows of all complete batches: of those folded by the last compact() from there, of later ones from their own folders."""
        marks = self._marks("commits")
        bases = self._marks("bases")
        last = max(bases, default=None)
        folded = set()
        paths = []
        if last is not None:
            base = self._path("base", f"{last}@{bases[last]}")
            folded = {r["batch"] for r in self.spark.read.parquet(f"{base}/batches").collect()}
            paths.append(f"{base}/{kind}")
        paths += [self._path(kind, f"{b}@{a}") for b, a in sorted(marks.items()) if b not in folded]
        reader = self.spark.read.schema(schema)
        frames = [reader.option("basePath", p).parquet(p) for p in paths]
        return reduce(DataFrame.unionByName, frames) if frames else self.spark.createDataFrame([], schema)

    def ledger(self, parts: list[int] | None = None) -> DataFrame:
        """What each document counts for: signed rows of all batches, summed; of the given parts only."""
        rows = self._read("ledger", LEDGER)
        rows = rows if parts is None else rows.filter(F.col("part").isin(parts))
        return rows.groupBy("part", "doc_id", *KEY).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens")).filter("docs <> 0 or tokens <> 0")

    def totals(self) -> DataFrame:
        rows = self._read("deltas", TOTALS)
        return rows.groupBy(*KEY).agg(F.sum("docs").alias("n_docs"), F.sum("tokens").alias("n_tokens")).filter("n_docs <> 0 or n_tokens <> 0")

    def signed(self, changes: DataFrame) -> DataFrame:
        """Signed ledger rows of changes (op, doc_id, source, lang, tokenizer, n_tokens, seq)."""
        part = F.pmod(F.xxhash64("doc_id"), F.lit(PARTS)).cast("int")
        counts = [F.lit(1).cast("long").alias("docs"), F.coalesce("n_tokens", F.lit(0)).cast("long").alias("tokens")]
        by = W.partitionBy("doc_id", "tokenizer").orderBy(F.desc_nulls_last("seq"), F.when(F.col("op") == "delete", 0).otherwise(1), F.desc_nulls_last("n_tokens"), F.desc_nulls_last("source"), F.desc_nulls_last("lang"))
        last = changes.filter("doc_id is not null").select("op", "doc_id", *KEY, "n_tokens", "seq").withColumn("part", part).withColumn("_rank", F.row_number().over(by)).filter("_rank = 1").drop("_rank")
        touched = [r["part"] for r in changes.filter("doc_id is not null").select(part.alias("part")).distinct().collect()]  # PARTS rows at most
        there = self.ledger(touched)
        keys = last.select(F.col("part").alias("p"), F.col("doc_id").alias("d"), F.col("tokenizer").alias("t"))
        same = (F.col("part") == F.col("p")) & (F.col("doc_id") == F.col("d")) & F.col("tokenizer").eqNullSafe(F.col("t"))
        gone = there.join(keys, same, "left_semi").select("part", "doc_id", *KEY, (-F.col("docs")).alias("docs"), (-F.col("tokens")).alias("tokens"))
        new = last.filter("op <> 'delete'").select("part", "doc_id", *KEY, *counts)
        # rows without an id can't be told apart later, so their sum by key will do
        bare = changes.filter("doc_id is null and op <> 'delete'").select(*KEY, *counts).groupBy(*KEY).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        return gone.unionAll(new).unionAll(bare.select(F.lit(-1).alias("part"), F.lit(None).cast("long").alias("doc_id"), *KEY, "docs", "tokens"))

    def _write(self, rows: DataFrame, path: str) -> None:
        rows.repartition(PARTS, "part").write.mode("overwrite").partitionBy("part").parquet(path)

    @staticmethod
    def _delta(rows: DataFrame) -> DataFrame:
        return rows.groupBy(*KEY).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Applies a batch; False if it was there already."""
        if batch in self.committed():
            return False
        attempt = uuid.uuid4().hex
        at = self._path("ledger", f"{batch}@{attempt}")
        self._write(self.signed(changes), at)
        self._delta(self.spark.read.schema(LEDGER).parquet(at)).write.mode("overwrite").parquet(self._path("deltas", f"{batch}@{attempt}"))
        self._mark("commits", batch, attempt)
        return True

    def compact(self) -> None:
        """Folds all complete batches into one base, which later reads start from; totals stay as they are."""
        batches, attempt, number = self.committed(), uuid.uuid4().hex, f"{len(self._marks('bases')):08d}"
        base = self._path("base", f"{number}@{attempt}")
        self._write(self.ledger().select("part", "doc_id", *KEY, "docs", "tokens"), f"{base}/ledger")
        self._delta(self._read("deltas", TOTALS)).write.mode("overwrite").parquet(f"{base}/deltas")
        self.spark.createDataFrame([(b,) for b in batches], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{base}/batches")
        self._mark("bases", number, attempt)
