"""Stages take effect, keep clean documents and do what brute force or SQL does to their input."""

import duckdb
import pytest
from pyspark.sql import functions as F

from abilityrank.llm import cotraining, quality_rules, weighted_minhash

pipeline = pytest.importorskip("corpus_pipeline")
SF = "/root/testdata/sf0.01"


def cut_by_brute_force(rows, n=50):
    """doc_id -> text without the windows that a document with a smaller doc_id has."""
    first = {}
    for d, t in rows:
        w = (t or "").encode().split()
        for k in range(len(w) - n + 1):
            first[tuple(w[k : k + n])] = min(first.get(tuple(w[k : k + n]), d), d)
    out = {}
    for d, t in rows:
        w = (t or "").encode().split()
        gone = {x for k in range(len(w) - n + 1) if first[tuple(w[k : k + n])] < d for x in range(k, k + n)}
        if not gone:
            out[d] = t
        elif len(gone) < len(w):
            out[d] = b" ".join(x for i, x in enumerate(w) if i not in gone).decode()
    return out


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    before = docs
    for name, stage in pipeline.STAGES:
        after = stage(spark, before, SF)
        after = pipeline.materialise(after, name)
        if name == "best_fit_packing":
            assert {r["doc_id"] for r in after.select("doc_id").distinct().collect()} == {r["doc_id"] for r in before.collect()}
            break
        assert after.columns == docs.columns and after.count() <= before.count()
        assert after.select("doc_id").exceptAll(before.select("doc_id")).count() == 0
        if name == "quality_classifier":
            good = labels.where("quality = 1").join(before, "doc_id").count()
            assert labels.where("quality = 1").join(after, "doc_id").count() >= 0.98 * good
            assert after.count() < before.count()
        pairs = [(r["doc_id"], r["text"]) for r in before.select("doc_id", "text").collect()]
        if name == "quality_classifier":
            scored = cotraining.score_documents(before, labels).where("kept").select("doc_id").collect()
            assert sorted(r["doc_id"] for r in scored) == sorted(r["doc_id"] for r in after.select("doc_id").collect())
        if name == "quality_rules":
            before.write.parquet(f"{tmp_path}/in")
            con = duckdb.connect()
            con.execute(f"create view documents as select * from '{tmp_path}/in/*.parquet'")
            want = con.execute(f"select doc_id from ({quality_rules.oracle()}) where kept order by 1").fetchall()
            assert [x for x, in want] == sorted(r["doc_id"] for r in after.select("doc_id").collect())
        if name == "near_duplicates":
            classes = weighted_minhash.near_duplicates(before).collect()  # held against all pairs in test_corpus
            assert {r["class_id"] for r in classes} == {r["doc_id"] for r in after.collect()}
        if name == "repeated_passages":
            assert {r["doc_id"]: r["text"] for r in after.collect()} == cut_by_brute_force(pairs)
            changed = after.select("doc_id", F.col("text").alias("new")).join(before, "doc_id").where("new <> text")
            assert changed.count() > 0 and changed.where("length(new) >= length(text)").count() == 0
        before = after


def test_names_and_odd_rows(spark):
    assert [n for n, _ in pipeline.STAGES] == ["quality_classifier", "quality_rules", "near_duplicates", "repeated_passages", "best_fit_packing"]
    rows = [(None, None, None, None, None), (1, "", "en", "s", 0), (2, "a text of a few words that says not very much at all", "en", "s", 50), (2, "a text of a few words that says not very much at all", "en", "s", 50)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("root", F.lit(1))
    for _, stage in pipeline.STAGES:
        stage(spark, docs, SF).count()
        stage(spark, docs.where("1 = 0"), SF).count()
