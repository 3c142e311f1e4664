from __future__ import annotations

import numpy as np
import pytest

from passage_engine.models import encoder, training
from passage_engine.models.encoder import Block, Config, Network
from passage_engine.plans import infer
from passage_engine.plans.windows import Adaptive, Fixed

SMALL = dict(vocab=64, width=8, heads=2, layers=1, max_tokens=40, max_sents=8, context=6)


def blocks(n=4, seed=0, phones=False):
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(n):
        sents = [rng.integers(4, 64, rng.integers(1, 6)).tolist() for _ in range(int(rng.integers(2, 6)))]
        ph = [[[int(x) for x in rng.integers(1, 8, rng.integers(0, 4))] for _ in s] for s in sents] if phones else None
        out.append(Block(sents, ph, [int(s[-1] < 20) for s in sents]))
    return out


@pytest.mark.parametrize("kind", ["block", "local", "two_level", "recurrent"])
def test_gradients_by_differences(kind):
    cfg = Config(kind=kind, **SMALL, phones=8 if kind == "block" else 0)
    params, data = encoder.init(cfg), blocks(3, phones=kind == "block")
    grads, _, _ = training.gradients(data, cfg, params, 0.0, 0)
    rng = np.random.default_rng(1)
    for name in params:
        for _ in range(2):
            at = tuple(int(rng.integers(0, s)) for s in params[name].shape)
            eps, old = 1e-5, params[name][at]
            values = []
            for d in (eps, -eps):
                params[name][at] = old + d
                values.append(float(Network(cfg, params).loss(data)[0].value))
            params[name][at] = old
            numeric = (values[0] - values[1]) / (2 * eps)
            assert abs(numeric - (grads[name][at] if name in grads else 0.0)) < 1e-4 * max(1, abs(numeric)), name


@pytest.mark.parametrize("kind", ["block", "local", "two_level", "recurrent"])
def test_learning_lowers_the_loss(kind):
    cfg = Config(kind=kind, **SMALL)
    _, losses = training.fit_local(blocks(40), cfg, epochs=6, batch=8, rate=1e-2, dropout=0.0)
    assert losses[-1] < losses[0] * 0.9


def test_padding_does_not_change_probabilities():
    cfg = Config(**SMALL)
    net, data = Network(cfg, encoder.init(cfg)), blocks(5)
    together = net.probabilities(data)[0]
    for b, p in zip(data, together):
        assert np.allclose(net.probabilities([b])[0][0], p, atol=1e-9)


def test_zero_phone_table_changes_nothing_and_mean_is_sum_over_count():
    cfg = Config(**SMALL, phones=8)
    params = encoder.init(cfg)
    data = blocks(3, phones=True)
    params["phone"] = np.zeros_like(params["phone"])
    plain = {k: v for k, v in params.items() if k != "phone"}
    a = Network(cfg, params).probabilities(data)[0]
    b = Network(Config(**SMALL), plain).probabilities([Block(x.sents, None, x.labels) for x in data])[0]
    assert all(np.allclose(x, y) for x, y in zip(a, b))
    one = [Block([[5]], [[[2, 2]]], [1])]
    params["phone"] = np.random.default_rng(0).standard_normal(params["phone"].shape)
    mean = Network(cfg, params).probabilities(one)[0][0]
    single = Network(cfg, params).probabilities([Block([[5]], [[[2]]], [1])])[0][0]
    assert np.allclose(mean, single)


def test_published_sizes():
    assert 105e6 < encoder.n_params(encoder.BASE) < 115e6
    assert 325e6 < encoder.n_params(encoder.LARGE) < 345e6


def test_checkpoint_round_trip():
    cfg = Config(**SMALL)
    params = encoder.init(cfg)
    cfg2, params2 = encoder.load(encoder.save(cfg, params))
    assert cfg2 == cfg and all((params[k] == params2[k]).all() for k in params)


def live(n, seed=0):
    rng = np.random.default_rng(seed)
    for d in range(n):
        words = [["w"] * int(rng.integers(1, 30)) for _ in range(int(rng.integers(0, 40)))]
        yield infer.Live(d, words, [len(w) for w in words])


@pytest.mark.parametrize("how", ["latest", "earliest", "max", "mean"])
def test_context_free_scores_do_not_depend_on_schedule_or_batch(how):
    def score(_, where):
        return [np.array([((d * 7 + i) % 10) / 10 for i in range(a, b + 1)]) for d, a, b in where], 1

    seen = []
    for policy in (Fixed(1), Fixed(5), Adaptive(4)):
        for batch in (1, 7):
            rows = infer.frontier(live(30), score, policy, batch, 100, 12, how)
            seen.append({r[0]: (np.round(r[2], 9).tolist(), list(r[3])) for r in rows})
    assert all(s == seen[0] for s in seen)


def test_half_nan_and_null_are_negative():
    assert not infer.positive(0.5, 0.5) and not infer.positive(float("nan"), 0.5) and infer.positive(0.5001, 0.5)
