"""Inference's lean pass against the differentiable one, and its memory."""

from __future__ import annotations

import tracemalloc

import numpy as np
import pytest

from passage_engine.experiments.learned import LARGER, TOY
from passage_engine.models import encoder
from passage_engine.models.training import as_blocks

KINDS = {"block": {}, "local": {}, "local, larger": {**LARGER, "context": 48}, "two_level": {}, "joint": {"joint": True}, "recurrent": {}, "block, phones": {"phones": 32}}


def made(name: str, docs: int):
    cfg = encoder.Config(**{**TOY, **KINDS[name], "kind": "two_level" if name == "joint" else name.split(",")[0]})
    rng = np.random.default_rng(3)
    params = {k: v + 0.3 * rng.standard_normal(v.shape) for k, v in encoder.init(cfg).items()}
    sents = [[[f"w{rng.integers(500)}" for _ in range(rng.integers(1, 13))] for _ in range(rng.integers(1, 20))] for _ in range(docs)] + [[["w1"]], [["w2"] * 300, ["w3"]]]
    return cfg, params, as_blocks(sents, None, cfg, {f"w{i}": ["a", "b"][: i % 3] for i in range(500)} if cfg.phones else None)


@pytest.mark.parametrize("name", KINDS)
def test_same_as_the_differentiable_pass(name):
    cfg, params, blocks = made(name, 12)
    mine, tokens = encoder.Network(cfg, params).probabilities(blocks)
    theirs, same = encoder.Network(cfg, params, train=True).probabilities(blocks)
    assert tokens == same and [len(x) for x in mine] == [len(b.sents) for b in blocks]
    for a, b in zip(mine, theirs, strict=True):
        np.testing.assert_allclose(a, b, rtol=0, atol=1e-12)


@pytest.mark.parametrize("name", ["block", "local, larger"])
def test_arrays_stay_small(name):
    cfg, params, blocks = made(name, 48)
    net = encoder.Network(cfg, params)
    tracemalloc.start()
    net.probabilities(blocks)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 15e6
