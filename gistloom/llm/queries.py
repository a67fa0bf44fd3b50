"""The driver's queries for the training-data operators: thin, whole tables, production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gistloom.llm import decontaminate, jaccard_join, line_dedup, mixing, pii, quality_model, quality_rules, toxicity, urls, warc
from gistloom.llm.oracle import ORACLES
from gistloom.llm.shared import table


def op1_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = jaccard_join.similarity_components(table(spark, sf_dir, "documents"), width=3, percent=90)
    return found.select("doc_id", "n_shingles", "component_id")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality_rules.apply_policy(quality_rules.ledger(table(spark, sf_dir, "documents")))
    base = F.col("failures").bitwiseAND(F.lit(quality_rules.BASE)) != 0
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), "kept", "failures")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = line_dedup.with_removals(table(spark, sf_dir, "documents"))
    places = F.coalesce("_gl_removed", F.array().cast("array<int>"))
    return done.select(
        "doc_id", F.size(places).cast("long").alias("n_removed"), F.coalesce("_gl_words", F.lit(0)).cast("long").alias("removed_words"),
        F.array_join(places.cast("array<string>"), ",").alias("removed_lines"), F.sha2(F.coalesce("_gl_text", F.lit("")), 256).alias("text_sha256"),
    )


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(table(spark, sf_dir, "documents"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages"))


def op6_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages"))


def op7_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).drop("positions").withColumn("target", F.round("target", 4)).withColumn("position", F.round("position", 6))


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality_model.score(docs, quality_model.train(docs, table(spark, sf_dir, "labels")))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


QUERIES = {f.__name__: f for f in (op1_ngram_jaccard, op2_quality_rules, op3_line_dedup, op4_pii, op5_url_filter, op6_warc, op7_source_mix, op8_quality_classifier, op9_toxicity, op10_decontamination)}


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
