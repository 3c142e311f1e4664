"""Sentences and paragraphs keep every character but the blanks at their ends, as in the SQL twins."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from passage_engine.functions import local
from passage_engine.functions import text as t

#: Pieces that begin or end with digits of their own place, with blanks of several kinds, or are blanks alone.
ROWS = [
    (0, "0 first. 1 second 1.  2 third 2\n1219 next? 42 2424 end\n  \n　wide . 0", "en"),
    (1, " a! 11 b\n1\n2222\n33 c. 1", "de"),
    (2, ". ".join(f"{i}{i} x{i}" for i in range(140)) + ". 0", "fr"),
    (3, None, "en"),
]
TURNS = [(i, k, "a", text) for i, (_, text, _) in enumerate(ROWS) for k in range(2) if text]


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("odd"))
    spark.createDataFrame(ROWS, "doc_id long, text string, lang string").coalesce(1).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(TURNS, "conv_id long, turn long, role string, text string").coalesce(1).write.parquet(f"{path}/conversations.parquet")
    return path


@pytest.mark.parametrize("key", ["acc_lecture", "acc_second_lang", "acc_written_cue", "agg_prf", "headline_work", "sweep_adaptive_work", "windows_adaptive"])
def test_as_sql(spark, odd, key):
    con = duckdb.connect()
    for name in ("documents", "conversations"):
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '{odd}/{name}.parquet/*.parquet'")
    mine = sorted(map(tuple, entry.queries()[key](spark, odd).collect()))
    assert mine and mine == sorted(con.execute(entry.oracle_sql()[key]).fetchall())


def test_as_plain_python(spark):
    df = spark.createDataFrame([r for r in ROWS if r[1]], "doc_id long, text string, lang string")
    for r in t.with_sentences(df).select("text", F.transform("sents", lambda s: s["text"]).alias("s")).collect():
        assert r.s == local.all_sentences(r.text)
