"""The registry against DuckDB on the smallest tables."""

from __future__ import annotations

import duckdb
import pytest

from tallymill.workloads.queries import ORACLE, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: The samplers over all tokens take the longest; the driver runs every one.
SHORT = [n for n in ORACLE if not n.startswith(("lda_", "dag_"))] + ["lda_sem_sweep_exact", "lda_sem_sweep_combined"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", SHORT)
def test_query_equals_sql(name, spark, duck):
    got, want = QUERIES[name](spark, SF).toPandas(), duck.sql(ORACLE[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True) for x in (got, want))
    assert a.astype(object).equals(b.astype(object)) or ((a == b) | (a.isna() & b.isna())).all().all()


@pytest.mark.parametrize("name", ["counter_moments_table", "counter_pmf", "counter_range_plan", "counter_read_table", "size_table_cm", "size_table_combined"])
def test_reads_a_table(name, spark):
    assert QUERIES[name](spark, SF).inputFiles()


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
