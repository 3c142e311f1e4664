from __future__ import annotations

from pyspark.sql import functions as F

from passage_engine.functions import phones as ph
from passage_engine.functions import text as t
from passage_engine.operators import annotate, evaluation
from passage_engine.sources import corpora


def test_sentences_and_labels(spark):
    df = spark.createDataFrame([(1, "One two. Three!\nFour? Five"), (2, ""), (3, None), (4, "\n\n"), (5, "no mark")], "doc_id long, text string")
    got = {r.doc_id: [(s.text, s.n_tok, s.ends_para) for s in r.sents] for r in t.with_sentences(df).collect()}
    assert got[1] == [("One two.", 2, False), ("Three!", 1, True), ("Four?", 1, False), ("Five", 1, True)]
    assert got[2] == got[3] == got[4] == [] and got[5] == [("no mark", 2, True)]


def test_blank_line_mode(spark):
    df = spark.createDataFrame([(1, "A b.\nC d.\n\nE.")], "doc_id long, text string")
    assert [s.ends_para for s in t.with_sentences(df, mode="blank_line").first().sents] == [False, True, True]


def test_hierarchy_levels(spark):
    df = spark.createDataFrame([(1, 0, [1, 1], "A. B."), (1, 1, [1, 2], "C."), (1, 2, [2, 1], "D.")], "doc_id long, pos int, path array<int>, text string")
    low = corpora.from_hierarchy(df, 2).first().sents
    high = corpora.from_hierarchy(df, 1).first().sents
    assert [s.ends_para for s in low] == [False, True, True, True]
    assert [s.ends_para for s in high] == [False, False, True, True]


def test_prf_leaves_the_last_sentence_out(spark):
    df = spark.createDataFrame([([True, False, True], [True, True, True]), ([True], [True]), ([], [])], "p array<boolean>, r array<boolean>")
    r = evaluation.document_prf(df, "p", "r").first()
    assert (r.tp, r.fp, r.fn, r.p, r.r) == (1, 0, 1, 1.0, 0.5) and r.p >= r.f1 >= r.r
    none = evaluation.document_prf(df.where("size(p) = 1"), "p", "r").first()
    assert (none.p, none.r, none.f1) == (0.0, 0.0, 0.0)


def test_voting_golden_case(spark):
    votes = {1: "1010", 2: "1010", 3: "1000", 4: "0111", 5: "1011"}
    rows = [(1, i, 4, a, int(v[i]), True) for a, v in votes.items() for i in range(4)]
    df = spark.createDataFrame(rows, "doc_id long, idx int, n_sent int, annotator int, vote int, ends_para boolean")
    loo = {r.annotator: r["rank"] for r in annotate.leave_one_out(df).collect()}
    assert loo[4] == 5
    for got in (annotate.vote(df, 4, 3), annotate.majority(df, 3)):
        assert [r.is_boundary for r in got.orderBy("idx").collect()] == [True, False, True, False]


def test_effective_returns(spark):
    rows = [(1, 1, "m", 1, "q", 1, 6.0), (2, 1, "m", 2, "q", 0, 20.0), (3, 1, "m", 3, "q", 1, 20.1), (4, 1, "m", 4, "q", None, 9.0), (5, 1, "m", 5, "q", 1, 9.0), (6, 1, "n", 5, "q", 1, 9.0)]
    df = spark.createDataFrame(rows, "job_id long, doc_id long, model string, worker_id long, question string, correct int, minutes double")
    assert sorted(r.job_id for r in annotate.effective(df).collect()) == [1, 2]
    assert annotate.answer_accuracy(df).first().accuracy == 0.5


def test_pk_and_window_diff(spark):
    df = spark.createDataFrame([([False, True, False, False, False], [False, True, False, False, False]), ([False] * 5, [False, True, False, True, False])], "p array<boolean>, r array<boolean>")
    rows = df.select(evaluation.pk(F.col("p"), F.col("r"), 2).alias("pk"), evaluation.window_diff(F.col("p"), F.col("r"), 2).alias("wd")).collect()
    assert rows[0].pk == rows[0].wd == 0.0 and rows[1].pk == rows[1].wd == 1.0


def test_significance(spark):
    rows = [(d, 5, 1, 1, 1, 5, 5) for d in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, tp_a long, fp_a long, fn_a long, tp_b long, fp_b long, fn_b long")
    assert evaluation.randomization(df, 200).first().p < 0.02
    assert evaluation.bootstrap(df, 100).first().p == 0.0
    assert abs(evaluation.chi2_p(3.841) - 0.05) < 1e-3


def test_phone_keys_and_entries(spark):
    df = spark.createDataFrame([("Physch",), ("fix",), ("thick",), ("tik",), ("été",)], "word string")
    got = {r.word: r.k for r in df.select("word", ph.phone_key(F.col("word")).alias("k")).collect()}
    assert got["Physch"] == "fyX" and got["fix"] == "fik" and got["thick"] == "Tik" and got["tik"] == "tik" and got["été"] == "ete"
    lex = ph.lexicon(df)
    assert {r.word for r in lex.where("rank = 2").collect()} == {"Physch", "thick"}
    assert ph.first_entry(lex).count() == 5


def test_noise_kinds(spark):
    s = spark.createDataFrame([(1, 0, "ab cd ap ef"), (1, 1, "zz")], "doc_id long, idx int, text string")
    lex = ph.lexicon(ph.vocabulary(s))
    pairs = ph.confusions(lex)
    assert {(r.word, r.next) for r in pairs.collect()} == {("ab", "ap"), ("ap", "ab")}
    swapped = {r.idx: r.hyp for r in ph.corrupt(s, pairs, 1.0).collect()}
    assert swapped == {0: "ap cd ab ef", 1: "zz"}
    twice = {r.idx: r.hyp for r in ph.corrupt(s, pairs, 1.0, ("repetition",)).collect()}
    assert twice[1] == "zz zz"
    gone = {r.idx: r.hyp for r in ph.corrupt(s, pairs, 1.0, ("deletion",)).collect()}
    assert gone == {0: "", 1: ""}


def test_segments_and_render(spark):
    df = spark.createDataFrame([("A b. C d.\nE f.",)], "text string")
    s = t.with_sentences(df.selectExpr("1L doc_id", "text"))
    flags = F.transform("sents", lambda x: x["ends_para"])
    r = s.select(t.segments(flags).alias("g"), t.render(F.col("sents"), flags).alias("v")).first()
    assert [tuple(x) for x in r.g] == [(0, 1), (2, 2)] and r.v == "A b. C d.\nE f."


def test_restored_marks(spark):
    df = spark.createDataFrame([("we saw it The end".split(),)], "w array<string>")
    assert df.select(ph.restore_marks(F.col("w")).alias("m")).first().m == ["", "", ".", "", "."]
