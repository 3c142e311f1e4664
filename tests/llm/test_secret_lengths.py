"""Random strings are found whatever digits they hold."""

from __future__ import annotations

import numpy as np

from passage_engine.llm import secrets


def test_random_strings_of_few_digits_are_found(spark, small):
    model = secrets.fit(spark.read.parquet(f"{small}/documents.parquet"))
    rng = np.random.default_rng(11)
    for letters in (secrets.ALPHABET[:64], secrets.ALPHABET[:52]):
        for n in (16, 20, 24, 32):
            words = ["".join(rng.choice(list(letters), n)) for _ in range(200)]
            found = [[k for k, _, _ in secrets.spans_of(f"see {w} here", model)[1]] == ["markov"] for w in words]
            assert sum(found) >= 190
    assert secrets.spans_of("see internationalization-of-everything and responsibilities_of_all", model) == ([], [])
