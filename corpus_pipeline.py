"""The corpus pipeline: documents through five stages, each on all that the one before it kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from abilityrank.llm import cotraining, fingerprint_index, packing, quality_rules, weighted_minhash
from abilityrank.llm.shared import materialise, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier does not reject."""
    return cotraining.keep_good(docs.select(COLUMNS), table(spark, sf_dir, "labels"))


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that keep the base rule and the rule table."""
    return quality_rules.apply_rules(docs.select(COLUMNS)).where("kept").select(COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each class of near-duplicates."""
    docs = docs.select(COLUMNS)
    first = weighted_minhash.near_duplicates(docs).where("doc_id = class_id").select("doc_id", F.lit(True).alias("_first")).distinct()
    kept = docs.join(first, "doc_id", "left").where("doc_id is null or _first")
    return kept.withColumn("_text", F.xxhash64("text")).dropDuplicates(["doc_id", "_text"]).select(COLUMNS)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the windows that an earlier document has; documents left without words go.

    A text that loses nothing keeps its bytes; another becomes its kept words, joined by spaces."""
    cut = fingerprint_index.dedup_substrings(docs.select(COLUMNS), with_text=True, extra=COLUMNS[2:]).where("n_removed < n_words or n_removed = 0")
    return cut.select("doc_id", F.col("kept_text").alias("text"), "lang", "source", F.when(F.col("n_removed") == 0, F.col("n_chars")).otherwise(F.length("kept_text")).cast("long").alias("n_chars"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document stands in the training sequences."""
    return packing.pack(docs.select(COLUMNS))


STAGES = [
    ("quality_classifier", quality_classifier),
    ("quality_rules", rules),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("best_fit_packing", pack),
]

#: Training, sampling and fingerprint joins are not SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
