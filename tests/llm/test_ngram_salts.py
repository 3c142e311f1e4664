"""Members of a group that is dealt out by a salt meet, however small the parts are."""

from __future__ import annotations

import random

import pytest
from test_operators import brute_components, docs_of

from passage_engine.llm import ngram_join

LINE = "one line that very many of the texts hold alike"


@pytest.mark.parametrize("small_group,salt_at", [(32, 4), (1000, 8), (32, 20_000)])
def test_short_documents_of_a_frequent_line_link_across_salts(spark, small_group, salt_at):
    rows = [(i, f"{LINE} " + " ".join(f"u{i}x{j}" for j in range(60))) for i in range(40)]
    rows += [(100 + i, f"{LINE} s{i}") for i in range(12)]
    want = brute_components(rows)
    assert {want[100 + i][1] for i in range(12)} == {100}
    df = docs_of(spark, [(i, t, "s") for i, t in rows])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similarity_components(df, small_group=small_group, salt_at=salt_at, block=5).collect()}
    assert got == want


def mixtures(seed=11):
    """264 rows: lines that many texts share, near copies at the border of similarity, equal texts."""
    rng = random.Random(seed)
    lines = [" ".join(f"l{i}x{j}" for j in range(rng.randint(6, 30))) for i in range(7)]
    rows = []
    for i in range(240):
        parts = rng.sample(lines, rng.randint(1, 3))
        parts.insert(rng.randrange(len(parts) + 1), " ".join(f"o{i}x{j}" for j in range(rng.choice([0, 1, 2, 3, 5, 8, 30]))))
        rows.append((i, " ".join(p for p in parts if p)))
    return rows + [(1000 + i, rows[rng.randrange(240)][1].upper() if i % 2 else rows[i][1]) for i in range(24)]


@pytest.mark.parametrize("small_group,salt_at,block", [(32, 4, 4096), (32, 8, 16), (6, 20, 4096), (2, 20_000, 10), (300, 20_000, 4096)])
def test_mixtures_of_frequent_lines_equal_brute_force(spark, small_group, salt_at, block):
    rows = mixtures()
    assert len(rows) == 264
    df = docs_of(spark, [(i, t, "s") for i, t in rows])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similarity_components(df, small_group=small_group, salt_at=salt_at, block=block).collect()}
    assert got == brute_components(rows)
