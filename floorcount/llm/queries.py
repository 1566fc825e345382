"""Queries of the ten operators and the pipeline."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from floorcount.llm import byte_bpe, decontamination, jaccard_join, language_mix, legacy_archive, license_scan, line_winnow, quality_rules, sql, token_rollups, url_aliases
from floorcount.llm.scratch import Scratch

VOCABULARY = "byte_bpe_50k.tiktoken"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = license_scan.scan(table(spark, sf_dir, "documents").select("doc_id", "text"))
    names = F.array_join(F.transform("licenses", lambda x: x["license"]), ",")
    return found.select("doc_id", F.size("licenses").alias("n_licenses"), names.alias("licenses"), F.coalesce(F.array_max(F.transform("licenses", lambda x: x["coverage"])), F.lit(0.0)).alias("coverage"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality_rules.judge(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source"))
    counts = [F.col(f"measures.{m}").alias(m) for m in quality_rules.MEASURES if m != "n_lines"]
    return judged.select("doc_id", *counts, "base_failed", "kept", F.array_join("beyond", ",").alias("beyond"))


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontamination.scan(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
    return found.select(
        "doc_id", F.col("found.n_words").alias("n_words"), decontamination.n_hit().alias("n_hit"), F.size("found.items").cast("long").alias("n_items"),
        F.sha2(F.array_join("found.items", ",").cast("binary"), 256).alias("items_sha256"), decontamination.contaminated().alias("contaminated"),
    )


def op4_legacy_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = legacy_archive.archive_pages(table(spark, sf_dir, "pages"))
    return rows.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path(VOCABULARY)
    ids = byte_bpe.encode(table(spark, sf_dir, "documents").select("doc_id", "text"), path, public_tokenizers.PATTERN).select("doc_id", "token_ids")
    both = byte_bpe.decode(ids, path, public_tokenizers.PATTERN)
    return both.select("doc_id", (F.octet_length("token_ids") / 4).cast("long").alias("n_tokens"), F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = language_mix.identify_languages(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"))
    return found.select("doc_id", "held_out", F.col("language.main").alias("lang_pred"), F.col("language.score").alias("score"), F.array_join(F.transform("language.languages", lambda x: x["lang"]), ",").alias("languages"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    kept = line_winnow.dedup_lines(docs)
    gone = F.aggregate("removed", F.lit(0).cast("long"), lambda s, x: s + x["last"] - x["first"] + 1)
    return kept.select("doc_id", F.size("removed").cast("long").alias("n_runs"), gone.alias("n_removed"), F.length("text").cast("long").alias("kept_chars"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = url_aliases.judge_urls(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return judged.select("page_id", "host", "path", "rule", "verdict")


def op10_token_rollups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four batches over all documents: two tokenizers, counts revised without repeated lines, copies deleted; one batch twice."""
    docs = table(spark, sf_dir, "documents")
    rollup = token_rollups.Rollup(spark, Scratch(spark, "rollups").path("state"))
    row = lambda df, op, tokenizer, tokens, seq: df.select(F.lit(op).alias("op"), "doc_id", "source", "lang", F.lit(tokenizer).alias("tokenizer"), tokens.alias("n_tokens"), F.lit(seq).alias("seq"))
    first = docs.filter("text is not null").groupBy(F.sha2(F.col("text").cast("binary"), 256).alias("digest")).agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    copies = docs.select("doc_id", "source", "lang", F.sha2(F.col("text").cast("binary"), 256).alias("d")).join(first, F.col("d") == F.col("digest")).filter("doc_id > first")
    once = docs.withColumn("text", F.array_join(F.array_distinct(F.split("text", "\n", -1)), "\n"))
    revised = row(once, "revise", "words-1", token_rollups.counted(once, "words-1"), 1)
    for batch, changes in (
        ("0-words-1", row(docs, "insert", "words-1", token_rollups.counted(docs, "words-1"), 0)),
        ("1-words-2", row(docs, "insert", "words-2", token_rollups.counted(docs, "words-2"), 0)),
        ("2-revised", revised),
        ("3-copies", row(copies, "delete", "words-1", F.lit(None).cast("long"), 2).unionAll(row(copies, "delete", "words-2", F.lit(None).cast("long"), 2))),
        ("2-revised", revised),
    ):
        rollup.commit(batch, changes)
    return rollup.totals()


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = [op1_license_scan, op2_quality_rules, op3_decontamination, op4_legacy_archive, op5_byte_bpe, op6_language_id, op7_line_dedup, op8_jaccard_join, op9_url_filters, op10_token_rollups]
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op2_quality_rules": sql.OP2, "op3_decontamination": sql.OP3, "op4_legacy_archive": sql.OP4, "op7_line_dedup": sql.OP7, "op8_jaccard_join": sql.OP8, "op9_url_filters": sql.OP9, "op10_token_rollups": sql.OP10}
