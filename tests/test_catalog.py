"""Registered queries against their DuckDB twins on the smallest tables, and the driver's contract."""

from __future__ import annotations

import datetime
import decimal
import math

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = [
    "headline_work", "sweep_fixed_work", "sweep_adaptive_work", "corpus_stats", "split_sizes", "agg_prf", "acc_trivial", "cohesion_scores", "train_samples_fixed", "train_samples_ref", "overlong_pool",
    "render_segments", "ann_loo", "ann_vote4", "read_accuracy", "sig_mcnemar", "noise_words", "homophones", "pretrain_order", "pool_mean", "threshold_edge", "join_asof", "join_lateral", "agg_cube", "win_range",
    "segments_islands", "set_except", "fn_array", "subquery_exists", "stream_tumbling", "stream_dedup", "udtf_segments", "sink_roundtrip",
]


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    if isinstance(v, (float, decimal.Decimal)):
        return f"{round(float(v), 5) + 0.0:.5f}"
    if isinstance(v, bool):
        return str(v)
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    return v.isoformat() if isinstance(v, (datetime.date, datetime.datetime)) else str(v)


@pytest.fixture(scope="module")
def duck(tiny):
    con = duckdb.connect()
    con.sql("SET timezone='UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return con


@pytest.mark.parametrize("key", CHECKED)
def test_twin(spark, duck, tiny, key):
    df = entry.queries()[key](spark, tiny)
    cols = sorted(df.columns)
    mine = sorted(str([plain(r[c]) for c in cols]) for r in df.collect())
    cur = duck.execute(entry.oracle_sql()[key])
    names = [d[0] for d in cur.description]
    assert sorted(names) == cols
    theirs = sorted(str([plain(r[names.index(c)]) for c in cols]) for r in cur.fetchall())
    assert mine == theirs


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() == 3


def test_filters_and_columns_reach_the_scan(spark, tiny):
    from passage_engine.session import setting

    with setting(spark, "spark.sql.maxMetadataStringLength", "10000"):
        plan = entry.queries()["scan_parquet"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThan(l_quantity,45.0)" in plan and "l_tax" not in plan


def test_windows_need_no_shuffle_and_no_python(spark, tiny):
    from passage_engine.experiments.core import scored, with_windows
    from passage_engine.plans.windows import Adaptive
    from passage_engine.sources import corpora

    plan = with_windows(scored(corpora.written(spark, tiny)), Adaptive(10)).select("doc_id", "wins")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan
