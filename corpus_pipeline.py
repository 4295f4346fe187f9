"""A corpus pipeline: quality rules, near-duplicate removal, benchmark
decontamination, personal data, mixing.

Each stage takes all that its predecessor kept and returns the columns of
documents; the last adds what the mix takes of each document. Documents are
carried by their rows, not by doc_id alone, wherever ids may be missing or
repeated. Empty tables pass through; null texts fail the quality stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chargepath.llm import decontam, mixing, neardup, pii, quality
from chargepath.llm.common import cut, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep; the rows ride along, so no text is joined back.

    Null and short texts go; equal rows share a verdict; a missing language is one of its own; long texts are read whole.
    """
    judged = quality.judge(docs, docs.columns)
    return judged.where("kept").select(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: shingles of five words, similarity 0.8 or more.

    The least id of a group stays, rows without one last, ties by text; of equal rows one stays; texts without words are
    in no group and stay.
    """
    odd = docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 OR doc_id IS NULL")
    if odd.isEmpty():
        return _kept_rows(docs, "doc_id")
    # Ids that are missing or repeated: rows are numbered in the order of ids, those without one last.
    rows = cut(docs.orderBy(F.col("doc_id").asc_nulls_last(), "text").withColumn("_row", F.monotonically_increasing_id()))
    return _kept_rows(rows, "_row").select(*docs.columns)


def _kept_rows(docs: DataFrame, key: str) -> DataFrame:
    """The rows that stay; each has its own key."""
    linked = neardup.link(docs.select(F.col(key).alias("doc_id"), "text"), width=5, percent=80)
    return docs.join(linked.where("kept").select(F.col("doc_id").alias(key)), key, "left_semi").select(*docs.columns)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that benchmark passages do not contaminate; those without words stay, and all do if the benchmark is empty."""
    judged = decontam.contamination(docs, table(spark, sf_dir, "benchmark"))
    return judged.where(~F.col("contaminated")).select(*docs.columns)


def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data replaced by <EMAIL>, <IP>, <CARD>, <PHONE> or <SECRET>; null texts stay null."""
    found = pii.find_pii(docs, mask=True)
    return found.withColumns({"text": F.col("masked"), "n_chars": F.length("masked").cast(docs.schema["n_chars"].dataType)}).select(*docs.columns)


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of the mix, with the words that it takes of each (repeats counted); those without words are never taken."""
    mixed = mixing.mix_sources(docs, mixing.word_count(F.col("text")))
    return mixed.where("taken > 0")


STAGES = [
    ("quality rules", quality_stage),
    ("near duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("personal data", pii_stage),
    ("mixing", mix_stage),
]
#: MinHash joins and masked spans have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = cut(stage(spark, docs, sf_dir))
    return docs
