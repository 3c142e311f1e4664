"""Several models and schedules in one pass over the documents; models fitted in tasks of their own."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from passage_engine.experiments import learned
from passage_engine.models import encoder, training
from passage_engine.plans import infer
from passage_engine.plans.windows import Adaptive, Fixed
from passage_engine.sources import corpora

RUNS = [(kind, p) for kind in ("block", "local", "two_level", "recurrent") for p in (Fixed(1), Fixed(5), Adaptive(2), Adaptive(10))]


def test_runs_together_are_runs_apart(spark):
    """Decisions and work of runs that share passes are those of each alone; empty documents and corpora have rows."""
    rng = np.random.default_rng(3)
    sents = lambda n: [(i, " ".join(f"w{x}" for x in rng.integers(0, 60, rng.integers(1, 14))), 0, bool(rng.random() < 0.3)) for i in range(n)]
    docs = spark.createDataFrame([(i, sents(n)) for i, n in enumerate([0, 1, 5, 40, 63, 12, 7])], "doc_id long, sents array<struct<idx int, text string, n_tok int, ends_para boolean>>")
    blobs = {k: encoder.save(c := encoder.Config(kind=k, vocab=64, width=8, heads=2, layers=1, max_tokens=64, max_sents=9, context=6), encoder.init(c)) for k, _ in RUNS}
    got = infer.with_runs(docs.withColumn("corpus", F.lit("a")), [(blobs[k], p) for k, p in RUNS], batch=3, limit=63, cap=9)
    mine = {(r.run, r.doc_id): (r.boundary, r.passes, r.encoded) for r in got.collect()}
    theirs = {(i, r.doc_id): (r.boundary, r.passes, r.encoded) for i, (k, p) in enumerate(RUNS) for r in infer.with_model(docs, blobs[k], p, limit=63, cap=9).collect()}
    assert mine == theirs and len(mine) == 7 * len(RUNS)
    ref = {r.doc_id: [s.ends_para for s in r.sents] for r in docs.collect()}
    assert all(r.ref == ref[r.doc_id] for r in got.collect())
    rows = learned.run_rows([(blobs["block"], Adaptive(10))] * 2, {"a": docs, "none": docs.where("false")}).collect()
    assert {(r.corpus, r.run) for r in rows} == {(c, i) for c in ("a", "none") for i in (0, 1)}
    assert all(r.tp == 0 and r.f1 == 0 for r in rows if r.corpus == "none")


def test_windows_are_encoded_once():
    """Runs that meet at a window share its pass."""

    class Counting:
        cfg, seen = encoder.Config(), []

        def probabilities(self, blocks):
            self.seen += [tuple(map(tuple, b.sents)) for b in blocks]
            return [np.full(len(b.sents), 0.9) for b in blocks], sum(len(s) for b in blocks for s in b.sents)

    net, words = Counting(), [[f"a{i}"] * 3 for i in range(30)]
    block = training.as_blocks([words], None, net.cfg)[0]
    states = {r: infer.Live(1, words, [3] * 30, seen=[[] for _ in words]) for r in range(3)}
    rows = list(infer.together(iter([infer.Shared(("a", 1, []), [block], states)]), [net], [(0, Fixed(1)), (0, Fixed(4)), (0, Adaptive(5))], limit=30, cap=10))
    assert len(rows) == 3 and sum(r[5] for r in rows) > len(net.seen) == len(set(net.seen))


def test_works_apart(spark):
    """Models fitted in tasks equal those fitted one after the other."""
    docs = corpora.from_text(spark.createDataFrame([(i, "one two. three four!\nfive. six seven.") for i in range(4)], "doc_id long, text string"))
    cfgs = [encoder.Config(**learned.TOY), encoder.Config(kind="local", **learned.TOY)]
    for cfg, blob in zip(cfgs, learned.trained_apart(docs, cfgs), strict=True):
        mine, theirs = encoder.load(blob)[1], encoder.load(learned.trained(docs, cfg)[0])[1]
        assert all(np.allclose(mine[k], theirs[k], atol=1e-9) for k in theirs)
