"""The ten queries opN_<name>, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chargepath.llm import decontam, licenses, mixing, neardup, oracle, pii, quality, substrings, tokens, toxicity, urls
from chargepath.llm.common import table


def op1_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.judge(table(spark, sf_dir, "pages").select("page_id", "url"))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_pii(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", *pii.counts(F.col("base_spans")), F.sha2("base_spans", 256).alias("base_sha256"), "spans", F.regexp_count("spans", F.lit(":[0-9]+:")).cast("long").alias("n_spans"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(table(spark, sf_dir, "documents"), ["doc_id"])
    return judged.withColumns({c: F.round(c, 6) for c in ("class_distance", "common_distance")})


def op4_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", mixing.word_count(F.col("text")).alias("n"))
    return mixing.mix_sources(docs, F.col("n")).select("doc_id", "size", "source_size", "target", "taken")


def op5_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.count_tokens(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")


def op6_toxicity(spark: SparkSession, sf_dir: str, max_train: int = 8000) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    grammar = toxicity.fit(toxicity.training_rows(docs, table(spark, sf_dir, "labels"), max_train))
    return toxicity.score_toxicity(docs, grammar).select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.link(table(spark, sf_dir, "documents").select("doc_id", "text"), width=4, percent=80)


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontam.contamination(docs, table(spark, sf_dir, "benchmark")).drop("text")


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")


def op10_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), ["doc_id"])


QUERIES = {f.__name__: f for f in (op1_url_rules, op2_pii, op3_quality, op4_mix, op5_tokens, op6_toxicity, op7_near_duplicates, op8_decontamination, op9_licenses, op10_substrings)}
ORACLES = {"op3_quality": oracle.QUALITY, "op7_near_duplicates": oracle.NEAR_DUPLICATES, "op8_decontamination": oracle.DECONTAMINATION, "op9_licenses": licenses.scan_sql(), "op10_substrings": oracle.SUBSTRINGS}
