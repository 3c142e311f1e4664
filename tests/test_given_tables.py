"""Queries that once made their data up read a given table, with the results of their SQL."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry

READS = {
    "threshold_edge": "events",
    "sql_phones": "conversations",
    "source_transcript": "conversations",
    "model_sizes": "conversations",
    "cte_recursive": "orders",
}


@pytest.mark.parametrize("key", READS)
def test_reads_its_table(spark, small, key):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW {READS[key]} AS SELECT * FROM '{small}/{READS[key]}.parquet'")
    df = entry.queries()[key](spark, small)
    assert any(f.endswith(f"/{READS[key]}.parquet") for f in df.inputFiles())
    theirs = con.execute(entry.oracle_sql()[key])
    assert [c[0] for c in theirs.description] == df.columns
    assert sorted(map(repr, map(tuple, df.collect()))) == sorted(map(repr, theirs.fetchall()))
