"""Queries of the operators for training data, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltahop.llm import decontaminate, katz, license_scan, near_dup, preference, quality_rules, repetition, sentence_pieces, suffix_dedup, token_table


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return preference.preference_digest(table(spark, sf_dir, "conversations"))


def op2_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_token_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_table.read_token_tables(token_table.write_token_tables(table(spark, sf_dir, "documents")))


def op4_rule_ensemble(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality_rules.fit(docs, table(spark, sf_dir, "labels"))
    scored = quality_rules.score_documents(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", quality_rules.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op5_repetition_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repetition.repetition_coverage(table(spark, sf_dir, "documents"))


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_odd_sketch_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.near_duplicates(table(spark, sf_dir, "documents"), near_dup.NearDupConfig(shingle=2))


def op8_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents"))


def op9_suffix_array_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentence_pieces.encode_documents(table(spark, sf_dir, "documents"))


def op10_katz_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz.score_documents(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_preference_pairs, op2_template_decontamination, op3_token_tables, op4_rule_ensemble, op5_repetition_coverage, op6_suffix_dedup, op7_odd_sketch_near_dup, op8_license_rules, op9_suffix_array_pieces, op10_katz_backoff, pipeline)}
ORACLES = {"op1_preference_pairs": preference.oracle(), "op8_license_rules": license_scan.oracle()}
