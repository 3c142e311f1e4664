"""No two names share a surrogate, also when the rounds don't get all apart."""

from __future__ import annotations

import pytest
from test_operators import KEY, docs_of

from passage_engine.llm import pii


@pytest.mark.parametrize("rounds", [0, 2])
def test_more_names_than_rounds_tell_apart(spark, rounds):
    letters = "абвгдежзик"
    names = [f"{t} Н{a}{b}" for t in ("Г-н", "Г-жа") for a in letters for b in letters] + [f"Mr Xa{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(200)]
    rows = pii.resolve_names(docs_of(spark, [(i, n, "s") for i, n in enumerate(names)]), KEY, rounds=rounds).collect()
    assert len(rows) == len({(r.gender, r.name) for r in rows}) == len(names)
    assert len({r.surrogate for r in rows}) == len(names)


def test_forty_thousand_names_stay_apart(spark):
    from pyspark.sql import functions as F

    docs = spark.range(40_000).select(F.col("id").alias("doc_id"), F.concat(F.lit("Mr "), *(F.substring(F.lit(s), (F.floor(F.col("id") / d) % 26 + 1).cast("int"), 1) for d, s in ((17_576, "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), (676, "abcdefghijklmnopqrstuvwxyz"), (26, "abcdefghijklmnopqrstuvwxyz"), (1, "abcdefghijklmnopqrstuvwxyz"))), F.lit(" Wolff")).alias("text"))
    out = pii.pseudonymise(docs, KEY)
    assert out.select("text").distinct().count() == 40_000


def test_one_person_in_several_spellings_and_the_country_of_a_number(spark):
    rows = [(1, "Mrs Anna Holm. Mrs ANNA HOLM. Mrs Holm. Mr Paul Holm rang +49 30 1234567.", "s")]
    text = pii.pseudonymise(docs_of(spark, rows), KEY).first().text
    full, upper, family, other = text.split(". ")
    assert upper == "Mrs " + full[4:].upper() and family == "Mrs " + full.split()[2]
    assert other.split()[2] == full.split()[2] and "+49 " in other and "1234567" not in other
