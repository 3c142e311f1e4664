"""Windows of the punctuation model cover every word of a turn once."""

from __future__ import annotations

from pyspark.sql import functions as F

from passage_engine.experiments import learned


def test_windows_cover_all_words(spark):
    sizes = {1: 0, 2: 1, 3: 100, 4: 101, 5: 350}
    docs = spark.createDataFrame([(i, [str(j) for j in range(n)]) for i, n in sizes.items()], "doc_id long, sents array<string>")
    got = {i: [] for i in sizes}
    for r in learned.word_windows(docs).orderBy("doc_id", "first").collect():
        assert len(r.s) <= 100 and r.first == len(got[r.doc_id])
        got[r.doc_id] += [int(x) for x in r.s]
    assert got == {i: list(range(n)) for i, n in sizes.items()}


def test_all_held_out_words_are_scored(spark, tiny, monkeypatch):
    seen = []
    real = learned.evaluation.document_prf
    monkeypatch.setattr(learned.evaluation, "document_prf", lambda df, p, r: (seen.append(df), real(df, p, r))[1])
    learned.punct_model(spark, tiny)
    held = learned.words_as_sentences(learned.corpora.interviews(spark, tiny)).where("doc_id % 10 >= 8")
    want = held.agg(F.sum("n_sent")).first()[0]
    assert seen[0].agg(F.sum(F.size("p")), F.sum(F.size("r"))).first() == (want, want)
