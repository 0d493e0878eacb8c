"""Registered queries against their SQL."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
FAST = ["resp_supplier_brand", "resp_doc_features", "resp_nominal_guess", "passage_items", "diffprop_supplier_brand", "diffprop_deflated", "update_matrix", "components", "investment_rounds", "oriented_ranking", "kendall", "accuracy_by_region", "interval_answers", "stream_final_answers", "op7_quality_rules"]


def rows(found, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return [names[i] for i in order], sorted(tuple(str(r[i]) for i in order) for r in found)


@pytest.mark.parametrize("name", FAST)
def test_matches_sql(spark, name):
    queries, sql = entry.queries(), entry.oracle_sql()
    if name not in queries:
        pytest.skip("not in this build")
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = queries[name](spark, SF)
    want = con.execute(sql[name])
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(want.fetchall(), [c[0] for c in want.description])


def test_entry_and_names(spark):
    assert entry.entry(spark).count() == 10
    assert set(entry.oracle_sql()) <= set(entry.queries())
