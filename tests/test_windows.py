"""Golden traces, invariants and equality of the two forms of the windows."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from passage_engine.plans import windows as win
from passage_engine.plans.windows import Adaptive, Fixed, trace

GOLDEN = [
    (Fixed(3), set(), [(0, 4), (2, 6), (4, 8), (6, 10), (8, 11)]),
    (Adaptive(3), {3, 7}, [(0, 4), (4, 8), (8, 11)]),
    (Fixed(1), set(), [(0, 4), (4, 8), (8, 11)]),
    (Adaptive(3), set(), [(0, 4), (4, 8), (8, 11)]),
    (Adaptive(3), {4, 9}, [(0, 4), (5, 9), (10, 11)]),
    (Adaptive(3, "moves"), {1, 6}, [(0, 4), (2, 6), (7, 11)]),
    (Adaptive(3, "count"), {1, 6}, [(0, 4), (4, 8), (7, 11)]),
    (Fixed(5), set(), [(i, min(i + 4, 11)) for i in range(8)]),
]


@pytest.mark.parametrize("policy,positives,expected", GOLDEN)
def test_golden_traces(policy, positives, expected):
    assert trace([1] * 12, lambda i: i in positives, policy, limit=5, cap=60) == expected


def test_long_sentence_advances_by_one():
    assert trace([900, 3, 900], lambda i: False, Adaptive(10)) == [(0, 0), (1, 1), (2, 2)]


def test_invariants_on_random_documents():
    rng = random.Random(4)
    for _ in range(300):
        n = [rng.randint(1, 40) for _ in range(rng.randint(1, 60))]
        pos = {i for i in range(len(n)) if rng.random() < 0.3}
        b = rng.randint(1, 8)
        w = trace(n, lambda i: i in pos, Adaptive(b), limit=60, cap=10)
        assert [i for i in range(len(n)) if not any(a <= i <= z for a, z in w)] == []
        assert all(x[0] < y[0] for x, y in zip(w, w[1:]))
        assert all(z - a < 10 and (sum(n[a : z + 1]) <= 60 or a == z) for a, z in w)
        assert len(w) <= len(trace(n, lambda i: i in pos, Fixed(b), limit=60, cap=10))
        assert trace(n, lambda i: False, Adaptive(b), limit=60, cap=10) == trace(n, lambda i: False, Fixed(1), limit=60, cap=10)


def test_column_twin_equals_trace(spark):
    rng = random.Random(5)
    rows = []
    for d in range(40):
        n = [rng.randint(1, 300) for _ in range(rng.randint(0, 30))]
        rows.append((d, n, [rng.random() < 0.3 for _ in n]))
    df = spark.createDataFrame(rows, "doc_id long, n array<int>, p array<boolean>")
    for policy in (Fixed(5), Adaptive(10), Adaptive(3, "count")):
        got = {r.doc_id: [tuple(x) for x in r.w] for r in df.select("doc_id", win.window_array(F.col("n"), F.col("p"), policy, 511, 7).alias("w")).collect()}
        for d, n, p in rows:
            assert got[d] == trace(n, lambda i, p=p: p[i], policy, 511, 7), (d, policy)


def test_cut_and_trim(spark):
    rng = random.Random(6)
    rows = [(i, [rng.randint(1, 60) for _ in range(rng.randint(1, 40))]) for i in range(40)] + [(99, [5184])]
    df = spark.createDataFrame(rows, "i int, n array<int>")
    for r in df.select("i", "n", win.cut(F.col("n"), 200).alias("c"), win.trim(F.col("n"), 200).alias("t")).collect():
        assert r.t == win.trim_list(r.n, 200)
        assert sum(r.t) <= 200 and len(r.t) == len(r.n) and min(r.t) >= 1
        if sum(r.n) > 200:
            assert r.c == win.cut_list(r.n, 200) and sum(r.c) <= 200
            assert sum(r.t) == 200 or all(a == b for a, b in zip(r.t, r.n))


def test_forward_windows_count(spark):
    df = spark.createDataFrame([(n,) for n in range(0, 75)], "n int")
    for r in df.select("n", win.forward_windows(F.col("n"), 10, 60).alias("w")).collect():
        assert len(r.w) == -(-r.n // 10)
        assert all(x.last - x.first < 60 and x.last < r.n for x in r.w)


@pytest.mark.parametrize("null", [False, True])
def test_adaptive_windows_split_each_text_once(spark, tmp_path, null):
    """One split of a text in each corpus's plan, in no filter beside the fold; texts without a sentence have no window."""
    from passage_engine.experiments.core import windows_adaptive

    text = "One two. Three four!\nFive. " * 40
    rows = [(1, text, "en"), (2, text, "de"), (3, None if null else " \n", "en")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    got = windows_adaptive(spark, str(tmp_path))
    assert got._jdf.queryExecution().optimizedPlan().toString().count("regexp_replace(") == 2
    sents = [s for _ in range(40) for s in ("One two.", "Three four!", "Five.")]
    want = trace([len(s.split()) for s in sents], lambda i: (len(sents[i]) + i) % 7 == 0, Adaptive(10))
    for doc, corpus in ((1, "F-EN"), (2, "F-XX")):
        mine = got.where(f"doc_id = {doc}").orderBy("win_no").collect()
        assert [(r.win_no, r.first, r.last) for r in mine] == [(k, *w) for k, w in enumerate(want, 1)] and {r.corpus for r in mine} == {corpus}
    assert got.where("doc_id = 3").count() == 0
