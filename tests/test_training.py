"""Pre-training rows, partial sentences, gradients in a tree, the joint two-level encoder."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from passage_engine.experiments import learned
from passage_engine.functions import pretrain
from passage_engine.functions import text as t
from passage_engine.models import encoder, training
from passage_engine.plans import windows as win
from passage_engine.sources import corpora

CFG = encoder.Config(**learned.TOY)


def test_unrelated_partners_come_from_another_document(spark, tiny):
    docs = corpora.interviews(spark, tiny).cache()
    own = {r.doc_id: {s.text for s in r.sents} for r in docs.collect()}
    for rows, y in ((pretrain.next_pairs(docs), 0), (pretrain.order_triples(docs), 2)):
        got = [r for r in rows.collect() if r.y == y]
        assert len(got) > 50 and all(r.s2 for r in got)
        assert sum(r.s2 in own[r.doc_id] for r in got) <= 0.02 * len(got)
    assert pretrain.next_pairs(docs.limit(1)).count() == 0


def test_replaced_words_follow_frequency(spark, tiny):
    docs = corpora.interviews(spark, tiny)
    counted = pretrain.counted_words(docs)
    rows = pretrain.replace_tokens(docs, counted, 0.3).collect()
    new = [a for r in rows for a, b, y in zip(r.x, r.target, r.y, strict=True) if y]
    n = {r.word: r.n for r in counted.collect()}
    assert len(new) > 200 and np.mean([n[w] for w in new]) > 2 * np.mean(list(n.values()))


def test_partial_sentence_at_a_cut(spark):
    df = spark.createDataFrame([([4, 5, 6],), ([20, 1],), ([10],)], "n array<int>")
    whole = [r.k for r in df.select(win.cut(F.col("n"), 11).alias("k")).collect()]
    part = [r.k for r in df.select(win.cut(F.col("n"), 11, True).alias("k")).collect()]
    assert whole == [[4, 5], [11], [10]] and part == [[4, 5, 2], [11], [10]]


def test_gradients_in_a_tree_equal_one_sum(spark, tiny):
    train = corpora.interviews(spark, tiny).where("n_sent > 1").repartition(9)
    s = training.samples(train, max_sents=20, limit=127).cache()
    blob, losses = training.fit(s, CFG, epochs=2, batch=10_000, rate=1e-2, dropout=0.0)
    rows = s.collect()
    blocks = training.as_blocks([r.sents for r in rows], [r.labels for r in rows], CFG)
    params, adam = encoder.init(CFG), encoder.Adam(1e-2)
    for _ in range(2):
        g, loss, n = training.gradients(blocks, CFG, params, 0.0, 0)
        adam.step(params, {k: v / n for k, v in g.items()})
    got = encoder.load(blob)[1]
    assert len(losses) == 2 and abs(losses[1] - loss / n) < 1e-5
    assert all(np.allclose(got[k], params[k], atol=1e-5) for k in params)
    parts = spark.createDataFrame([(np.full(3, float(i)).tobytes(), 1.0, 2) for i in range(40)], "g binary, loss double, n long").repartition(40)
    one = training.summed(parts, 40, 4).collect()
    assert len(one) == 1 and np.frombuffer(one[0].g).tolist() == [780.0] * 3 and one[0].n == 80


def test_joint_two_level_sees_other_sentences():
    for joint in (False, True):
        cfg = encoder.Config(**{**learned.TOY, "kind": "two_level", "joint": joint})
        net = encoder.Network(cfg, encoder.init(cfg))
        rng = np.random.default_rng(0)
        sents = [rng.integers(4, 500, 6).tolist() for _ in range(5)]
        v, _, _ = net.sentence_vectors([encoder.Block(sents)])
        z, real, tokens = net.logits([encoder.Block(sents)])
        assert z.value.shape == (1, 5, 2) and real.all() and tokens == (31 if joint else 35)


def test_pretraining_lowers_its_loss(spark, tiny):
    docs = corpora.interviews(spark, tiny).where("n_sent > 1").cache()
    for name in learned.ENCODERS:
        params, losses = learned.warmed(name, docs, CFG, 4, 300)
        assert params["head.w"].shape == (16, 2)
        assert losses[-1] < losses[-4], name


def test_replacements_are_looked_up_by_bisection(spark):
    """Every drawn token gets the word that plain Python draws, and no list of the vocabulary is scanned for it."""
    import hashlib
    from bisect import bisect_right
    from itertools import accumulate

    docs = spark.createDataFrame([(7, " ".join(f"w{i % 9}" for i in range(60)) + ". w1 w2 w3 w4")], "doc_id long, text string")
    docs = t.with_sentences(docs)
    for most in (1, 4, 4096):
        rows = pretrain.replace_tokens(docs, pretrain.counted_words(docs), 0.5, most)
        assert "filter(sums" not in rows._jdf.queryExecution().analyzed().toString()
        h = lambda *x: int(hashlib.md5("-".join(map(str, x)).encode()).hexdigest()[:8], 16)
        counted = sorted(pretrain.counted_words(docs).collect(), key=lambda r: (-r.n, hashlib.md5(r.word.encode()).hexdigest()))[:most]
        pool = sorted((r.word, r.n) for r in counted)
        sums = list(accumulate(n for _, n in pool))
        for r in rows.collect():
            want = [pool[bisect_right(sums, h(r.doc_id, r.idx, i, "word") % sums[-1])][0] if h(r.doc_id, r.idx, i, "replace") % 1000 < 500 else w for i, w in enumerate(r.target)]
            assert r.x == want and r.y == [int(a != b) for a, b in zip(want, r.target, strict=True)]


def test_all_samples_train_all_models(spark, tiny):
    """Models fitted together, in slices and tasks, equal each one's steps on all samples at once; no step is left out."""
    train = corpora.interviews(spark, tiny).where("n_sent > 1").repartition(9)
    s = training.samples(train, max_sents=20, limit=127).cache()
    rows = s.collect()
    cfgs = [CFG, encoder.Config(**{**learned.TOY, "kind": "recurrent"})]
    got = training.fit_all(s, cfgs, epochs=2, steps=1, rate=1e-2, dropout=0.0)
    for cfg, (blob, losses) in zip(cfgs, got, strict=True):
        blocks = training.as_blocks([r.sents for r in rows], [r.labels for r in rows], cfg)
        params, adam = encoder.init(cfg), encoder.Adam(1e-2)
        for _ in range(2):
            g, loss, n = training.gradients(blocks, cfg, params, 0.0, 0)
            adam.step(params, {k: v / n for k, v in g.items()})
        mine = encoder.load(blob)[1]
        assert len(losses) == 2 and abs(losses[1] - loss / n) < 1e-5
        assert all(np.allclose(mine[k], params[k], atol=1e-5) for k in params)
    assert [len(losses) for _, losses in training.fit_all(s, cfgs, epochs=1, steps=3, batch=4)] == [3, 3]
    assert [losses for _, losses in training.fit_all(s.where("false"), cfgs)] == [[], []]


def test_transfer_trains_on_the_whole_part(spark, tiny, monkeypatch):
    """Samples of every document of the training part reach the models, of no other."""

    class Seen(Exception):
        pass

    def fit_all(samples, cfgs, *_, **__):
        raise Seen({r.doc_id for r in samples.select("doc_id").distinct().collect()}, [c.kind for c in cfgs])

    monkeypatch.setattr(training, "fit_all", fit_all)
    part = corpora.written(spark, tiny, True).where("n_sent > 1").where(t.h(t.key(F.col("doc_id"), "half")) % 10 < 8)
    want = {r.doc_id for r in part.select("doc_id").collect()}
    assert len(want) > learned.WRITTEN_DOCS
    try:
        learned.transfer(spark, tiny)
    except Seen as e:
        assert e.args == (want, ["block", "local", "two_level", "recurrent"])
    else:
        raise AssertionError("the models were not fitted by fit_all")
