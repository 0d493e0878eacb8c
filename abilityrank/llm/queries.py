"""Queries over the corpus tables: one for each operator, over its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import cotraining, fingerprint_index, kmeans_tree, licences, merge_dropout, packing, quality_rules, suffix_dedup, token_store, weighted_minhash
from .shared import shared_dir, table


def op1_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    store = token_store.TokenStore.write(docs, shared_dir(spark, "tokens"))
    return store.read(store.lookup(docs), digest=True)


def op2_kmeans_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kmeans_tree.neighbours(table(spark, sf_dir, "embeddings"))


def op3_cotraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cotraining.score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_weighted_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted_minhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_fingerprint_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_index.dedup_substrings(table(spark, sf_dir, "documents"))


def op6_vector_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_rules_report(table(spark, sf_dir, "documents"))


def op8_merge_dropout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merge_dropout.encode_documents(table(spark, sf_dir, "documents"))


def op9_licence_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan_licences(table(spark, sf_dir, "documents")).withColumn("spans", F.to_json("spans"))


def op10_induced_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.dedup_bytes(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_token_store, op2_kmeans_tree, op3_cotraining, op4_weighted_minhash, op5_fingerprint_runs, op6_vector_best_fit, op7_quality_rules, op8_merge_dropout, op9_licence_spans, op10_induced_suffixes)}


def oracle_sql() -> dict[str, str]:
    """Where SQL can express a query; the others are held against brute force in the tests."""
    return {"op7_quality_rules": quality_rules.oracle()}
