"""Queries and pipeline on the smallest tables."""

from __future__ import annotations

import duckdb
import pytest

import corpus_pipeline
from tallymill.llm import queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", queries.oracle_sql())
def test_queries_match_sql(spark, name):
    con = duckdb.connect()
    for t in ("conversations", "documents", "benchmark"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want, got = con.sql(queries.oracle_sql()[name]).df(), queries.queries()[name](spark, SF).toPandas()
    columns = list(want.columns)
    assert sorted(got.columns) == sorted(columns)
    want, got = (x[columns].sort_values(columns).reset_index(drop=True) for x in (want, got))
    assert got.equals(want)


def test_held_out_language(spark):
    truth = {r.doc_id: r.lang for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = queries.op6_language(spark, SF).collect()
    held = [r.lang_pred == truth[r.doc_id] for r in rows if r.held_out]
    assert len(rows) == 200 and sum(held) > 0.97 * len(held)


def test_pipeline(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.cut(stage(spark, docs, SF), "stage")
        assert docs.columns == columns
        assert before >= docs.count() > 0.5 * before
    assert corpus_pipeline.run(spark, SF).count() == docs.count()
