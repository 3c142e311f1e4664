"""Components by rounds, in one task and by plain union-find are the same."""

from __future__ import annotations

import random

import pytest

from passage_engine.llm.graph import components


@pytest.mark.parametrize("one_task", [0, 10, 500_000])
def test_components_equal_union_find(spark, one_task):
    rng = random.Random(4)
    edges = [(i, i + 1) for i in range(60)] + [(rng.randint(100, 400), rng.randint(100, 400)) for _ in range(150)] + [(500, 500), (700, 600), (700, 601)] + [(900, 901 + i) for i in range(80)]
    root: dict[int, int] = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    want = {x: find(x) for x in root if x != 500}
    got = components(spark.createDataFrame(edges, "a long, b long").repartition(6), one_task).collect()
    assert {r.node: r.root for r in got} == want and len(got) == len(want)
    assert components(spark.createDataFrame([], "a long, b long"), one_task).count() == 0
