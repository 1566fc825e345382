"""A corpus made ready for training: five stages over documents, each of one operator.

STAGES holds (name, function) pairs; a function takes (spark, docs, sf_dir) and returns the documents that stay. run()
applies them, writing each result and reading it again as the next stage's documents.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from floorcount.llm import byte_bpe, decontamination, jaccard_join, line_winnow, quality_rules
from floorcount.llm.queries import VOCABULARY, table
from floorcount.llm.scratch import Scratch

#: What the last stage wrote for itself; nothing reads it once the next one starts on that stage's written result.
_held: list[Scratch] = []


def _scratch(spark: SparkSession, name: str) -> Scratch:
    while _held:
        _held.pop().release()
    _held.append(Scratch(spark, name))
    return _held[-1]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rule and the fences of their language and source keep."""
    judged = quality_rules.judge(docs, scratch=_scratch(spark, "quality"), keep_text=True)
    return judged.filter("kept").select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the runs of lines that stand earlier; those of which no word is left go."""
    kept = line_winnow.dedup_lines(docs, scratch=_scratch(spark, "lines"))
    some = kept.filter((F.size("removed") == 0) | F.regexp_like("text", F.lit(line_winnow.WORD)))
    return some.withColumn("n_chars", F.when(F.size("removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: that with the smallest doc_id; of rows with one doc_id, one."""
    groups = _scratch(spark, "jaccard")
    found = groups.keep(jaccard_join.near_duplicates(docs, scratch=groups), "result")
    # only texts that may go are shuffled
    gone = found.filter("doc_id <> component_id").select(F.col("doc_id").alias("gone")).distinct()
    marked = jaccard_join.told(docs.filter("doc_id is not null"), "doc_id", gone)
    stay = marked.filter("may").join(gone, F.col("doc_id") == F.col("gone"), "left_anti")
    kept = marked.filter("not may").unionByName(stay).select(*docs.columns)
    if not found.filter("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").isEmpty():
        row = F.min(F.struct(F.col("text"), *[F.col(f"`{c}`") for c in docs.columns if c != "text"])).alias("row")
        kept = kept.groupBy("doc_id").agg(row).select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])
    return kept.unionByName(docs.filter("doc_id is null"))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which less than a twentieth of the words stand in a benchmark window."""
    _scratch(spark, "benchmark")
    return decontamination.scan(docs, table(spark, sf_dir, "benchmark"), to="found").filter(~decontamination.contaminated()).select(*docs.columns)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents' ids, without the text; intact: they decode to the text."""
    _scratch(spark, "ids")
    both = byte_bpe.round_trip(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)
    intact = F.col("decoded") == F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return both.select(*[c for c in docs.columns if c != "text"], "token_ids", (F.octet_length("token_ids") / 4).cast("long").alias("n_tokens"), intact.alias("intact"))


STAGES = [("quality rules", quality), ("line dedup", line_dedup), ("n-gram Jaccard join", near_duplicates), ("benchmark decontamination", decontaminate), ("byte-level BPE", tokenize)]

#: SQL can't express the byte-pair merges of the last stage; tests hold the pipeline against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over the documents of sf_dir."""
    docs = table(spark, sf_dir, "documents")
    kept = Scratch(spark, "pipeline")
    for k, (_, stage) in enumerate(STAGES):
        docs = kept.keep(stage(spark, docs, sf_dir), f"stage-{k}")
    return docs
