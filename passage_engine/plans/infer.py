"""Inference over document rows: windows that follow the model's decisions, without a shuffle.

Within a task, up to ``batch`` documents are live. Each round takes the next window of every live
document, orders them by size to save padding, makes one pass, records the decisions, computes the
next starts, retires finished documents and admits new ones.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as t
from ..models.encoder import Block, Network, load
from ..models.training import as_blocks
from .windows import MAX_SENTENCES, MAX_TOKENS, fit_last

OUT = "doc_id long, n_sent int, probs array<double>, boundary array<boolean>, win_no array<int>, n_seen array<int>, passes int, encoded int, tokens long, nanos long"


@dataclass
class Live:
    doc_id: int
    words: list[list[str]]
    n_tok: list[int]
    first: int = 0
    passes: int = 0
    encoded: int = 0
    tokens: int = 0
    nanos: int = 0
    seen: list[list[tuple[int, float]]] = field(default_factory=list)


def resolve(seen: list[tuple[int, float]], how: str) -> tuple[int, float]:
    """(window, probability) of a sentence from all windows that decided it."""
    if how == "earliest":
        return seen[0]
    if how == "max":
        return max(seen, key=lambda x: x[1])
    if how == "mean":
        return seen[-1][0], float(np.mean([p for _, p in seen]))
    return seen[-1]


def positive(p: float, threshold: float) -> bool:
    return p is not None and not np.isnan(p) and p > threshold


def advance(d: Live, a: int, b: int, p: np.ndarray, tokens: int, nanos: int, policy, how: str, threshold: float) -> tuple | None:
    """Record the decisions of window a to b; the row of OUT of a finished document, or None and the next start."""
    for i in range(a, b + 1):
        d.seen[i].append((d.passes, float(p[i - a])))
    d.passes += 1
    d.encoded += b - a + 1
    d.tokens += tokens
    d.nanos += nanos
    if b >= len(d.words) - 1:
        got = [resolve(s, how) for s in d.seen]
        return d.doc_id, len(d.words), [x for _, x in got], [positive(x, threshold) for _, x in got], [w for w, _ in got], [len(s) for s in d.seen], d.passes, d.encoded, d.tokens, d.nanos
    d.first = policy.next_start(a, b, lambda i: positive(d.seen[i][-1][1], threshold), len(d.words))
    return None


def frontier(docs: Iterator[Live], score: Callable[[list[list[list[str]]], list[tuple[int, int, int]]], tuple[list[np.ndarray], int]], policy, batch: int = 48, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES, how: str = "latest", threshold: float = 0.5) -> Iterator[tuple]:
    """Rows of OUT for each document. score: sentences of windows and (doc_id, first, last) to probabilities and tokens."""
    live: list[Live] = []
    more = True
    while True:
        while more and len(live) < batch:
            d = next(docs, None)
            if d is None:
                more = False
            elif not d.words:
                yield d.doc_id, 0, [], [], [], [], 0, 0, 0, 0
            else:
                d.seen = [[] for _ in d.words]
                live.append(d)
        if not live:
            return
        spans = [(d, d.first, fit_last(d.n_tok, d.first, limit, cap)) for d in live]
        spans.sort(key=lambda x: sum(x[0].n_tok[x[1] : x[2] + 1]))
        began = time.perf_counter_ns()
        probs, tokens = score([d.words[a : b + 1] for d, a, b in spans], [(d.doc_id, a, b) for d, a, b in spans])
        nanos = (time.perf_counter_ns() - began) // len(spans)
        total = sum(b - a + 1 for _, a, b in spans)
        still = []
        for (d, a, b), p in zip(spans, probs, strict=True):
            if row := advance(d, a, b, p, tokens * (b - a + 1) // total, nanos, policy, how, threshold):
                yield row
            else:
                still.append(d)
        live = still


def _rows(frames: Iterator[pd.DataFrame]) -> Iterator[Live]:
    for pdf in frames:
        for doc, words in zip(pdf.doc_id.tolist(), pdf.words.tolist(), strict=True):
            ws = [list(w) for w in words]
            yield Live(doc, ws, [len(w) for w in ws])


def _emit(rows: Iterator[tuple], out: str = OUT, size: int = 500) -> Iterator[pd.DataFrame]:
    names = [c.split()[0] for c in out.split(", ")]
    held: list[tuple] = []
    for r in rows:
        held.append(r)
        if len(held) >= size:
            yield pd.DataFrame(held, columns=names)
            held = []
    if held:
        yield pd.DataFrame(held, columns=names)


def document_words(corpus: DataFrame) -> DataFrame:
    return corpus.select("doc_id", F.transform("sents", lambda s: F.split(s["text"], t.SPACE)).alias("words"))


def balanced(corpus: DataFrame, parts: int | None = None) -> DataFrame:
    """Deal documents out by hash: one shuffle, so that long ones don't meet by chance of the files."""
    return corpus.repartition(parts, "doc_id") if parts else corpus


def with_model(corpus: DataFrame, blob: bytes, policy, lexicon: dict | None = None, batch: int = 48, how: str = "latest", threshold: float = 0.5, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> DataFrame:
    """Decisions of a trained network for each document of a corpus; see OUT for the columns."""
    sent = corpus.sparkSession.sparkContext.broadcast((blob, lexicon))

    def run(frames):
        cfg, params = load(sent.value[0])
        net = Network(cfg, params)

        def score(windows, _):
            return net.probabilities(as_blocks(windows, None, cfg, sent.value[1]))

        yield from _emit(frontier(_rows(frames), score, policy, batch, limit, cap, how, threshold))

    return document_words(corpus).mapInPandas(run, OUT)


def with_probs(corpus: DataFrame, probs: Column, policy, how: str = "latest", threshold: float = 0.5, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> DataFrame:
    """The same loop over probabilities known in advance; its windows equal the Column twin's."""
    rows = corpus.select("doc_id", F.transform("sents", lambda s: F.split(s["text"], t.SPACE)).alias("words"), probs.alias("given"))

    def run(frames):
        table: dict[int, list[float]] = {}

        def docs():
            for pdf in frames:
                for doc, words, given in zip(pdf.doc_id.tolist(), pdf.words.tolist(), pdf.given.tolist(), strict=True):
                    ws = [list(w) for w in words]
                    table[doc] = list(given)
                    yield Live(doc, ws, [len(w) for w in ws])

        def score(_, where):
            return [np.array(table[d][a : b + 1]) for d, a, b in where], sum(b - a + 1 for _, a, b in where)

        for r in frontier(docs(), score, policy, 48, limit, cap, how, threshold):
            table.pop(r[0], None)
            yield pd.DataFrame([r], columns=[c.split()[0] for c in OUT.split(", ")])

    return rows.mapInPandas(run, OUT)


RUNS_OUT = "corpus string, doc_id long, run int, boundary array<boolean>, ref array<boolean>, passes int, encoded int, tokens long, nanos long"


@dataclass
class Shared:
    """A document under several runs: their states, and what windows gave that any of them asked for."""

    keep: tuple  # corpus, doc_id, ref
    blocks: list[Block]  # of each model
    states: dict[int, Live]
    known: dict[tuple[int, int], tuple[int, np.ndarray, int, int]] = field(default_factory=dict)  # (model, first): last, probabilities, tokens, nanos


def together(docs: Iterator[Shared], nets: list[Network], runs: list[tuple[int, object]], batch: int = 48, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES, how: str = "latest", threshold: float = 0.5) -> Iterator[tuple]:
    """Rows of RUNS_OUT: ``frontier`` for several runs (place of a network, policy) over the same documents.

    A window is settled by its network and first sentence, so runs that meet at one share its pass; each
    counts the pass, and its time, as its own.
    """
    live: list[Shared] = []
    more = True
    while True:
        while more and len(live) < batch:
            if (d := next(docs, None)) is None:
                more = False
            else:
                live.append(d)
        if not live:
            return
        for m, net in enumerate(nets):
            wanted = []
            for d in live:
                for first in {x.first for r, x in d.states.items() if runs[r][0] == m and x.words and (m, x.first) not in d.known}:
                    n = [len(s) for s in d.blocks[m].sents]
                    last = fit_last(n, first, limit, cap)
                    wanted.append((sum(n[first : last + 1]), d, first, last))
            wanted.sort(key=lambda x: x[0])
            for i in range(0, len(wanted), batch):
                spans = [x[1:] for x in wanted[i : i + batch]]
                began = time.perf_counter_ns()
                probs, tokens = net.probabilities([Block(d.blocks[m].sents[a : b + 1], d.blocks[m].phones and d.blocks[m].phones[a : b + 1]) for d, a, b in spans])
                nanos = (time.perf_counter_ns() - began) // len(spans)
                total = sum(b - a + 1 for _, a, b in spans)
                for (d, a, b), p in zip(spans, probs, strict=True):
                    d.known[m, a] = b, p, tokens * (b - a + 1) // total, nanos
        for d in live:
            for r, x in list(d.states.items()):
                m, policy = runs[r]
                row = None if x.words else (x.doc_id, 0, [], [], [], [], 0, 0, 0, 0)
                while row is None and (m, x.first) in d.known:
                    last, p, tokens, nanos = d.known[m, x.first]
                    row = advance(x, x.first, last, p, tokens, nanos, policy, how, threshold)
                if row:
                    corpus, doc, ref = d.keep
                    yield corpus, doc, r, row[3], ref, *row[6:]
                    del d.states[r]
        live = [d for d in live if d.states]


def with_runs(corpus: DataFrame, runs: list[tuple[bytes, object]], lexicon: dict | None = None, batch: int = 48, how: str = "latest", threshold: float = 0.5, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES) -> DataFrame:
    """Decisions of several runs (model, policy) for each document, in one pass over the corpus; see RUNS_OUT.

    The documents (corpus, doc_id, sents) are dealt out by hash: files of a size differ in work.
    """
    spark = corpus.sparkSession
    blobs = list({b: None for b, _ in runs})
    sent = spark.sparkContext.broadcast((blobs, [(blobs.index(b), p) for b, p in runs], lexicon))

    def run(frames):
        blobs, plans, lexicon = sent.value
        nets = [Network(*load(b)) for b in blobs]
        space = re.compile(t.SPACE)

        def docs():
            for pdf in frames:
                for name, doc, texts, ref in zip(pdf.corpus.tolist(), pdf.doc_id.tolist(), pdf.texts.tolist(), pdf.ref.tolist(), strict=True):
                    words = [space.split(x) for x in texts]
                    made, took = {}, {}
                    for c in (net.cfg for net in nets):
                        if (k := (c.vocab, c.phones, c.phone_spread)) not in made:
                            began = time.perf_counter_ns()
                            made[k] = as_blocks([words], None, c, lexicon)[0]
                            took[k] = time.perf_counter_ns() - began
                    keys = [(net.cfg.vocab, net.cfg.phones, net.cfg.phone_spread) for net in nets]
                    n = [len(w) for w in words]
                    states = {r: Live(doc, words, n, nanos=took[keys[m]], seen=[[] for _ in words]) for r, (m, _) in enumerate(plans)}
                    yield Shared((name, doc, list(ref)), [made[k] for k in keys], states)

        yield from _emit(together(docs(), nets, plans, batch, limit, cap, how, threshold), RUNS_OUT)

    rows = corpus.select("corpus", "doc_id", F.transform("sents", lambda s: s["text"]).alias("texts"), F.transform("sents", lambda s: s["ends_para"]).alias("ref"))
    return balanced(rows, int(spark.conf.get("spark.sql.shuffle.partitions"))).mapInPandas(run, RUNS_OUT)


def predictions(decided: DataFrame) -> DataFrame:
    """One row a sentence: doc_id, idx, prob, is_boundary, win_no, n_seen."""
    z = F.arrays_zip("probs", "boundary", "win_no", "n_seen")
    return decided.select("doc_id", F.posexplode(z).alias("idx", "z")).select("doc_id", "idx", F.col("z.probs").alias("prob"), F.col("z.boundary").alias("is_boundary"), "z.win_no", "z.n_seen")


def chunked(corpus: DataFrame, size: int = 5000, overlap: int = MAX_SENTENCES) -> DataFrame:
    """Documents beyond ``size`` sentences in chunks that overlap by a window, so that no book holds a stage.

    Adds chunk and offset, by which ``merged`` puts documents together again. In the overlap the
    earlier chunk's decisions win; results may differ slightly from the whole document's.
    """
    starts = F.when(F.col("n_sent") > size, F.sequence(F.lit(0), F.col("n_sent") - 1 - overlap, F.lit(size - overlap))).otherwise(F.array(F.lit(0)))
    rows = corpus.select("doc_id", "sents", F.posexplode(starts).alias("chunk", "offset"))
    piece = F.slice("sents", F.col("offset") + 1, size)
    return rows.select("doc_id", "chunk", "offset", piece.alias("sents"), F.size(piece).alias("n_sent"))


def merged(decided: DataFrame, value: str = "boundary") -> DataFrame:
    """Decisions of chunks (doc_id, chunk, offset, value array) to one array a document."""
    lists = decided.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("chunk", "offset", F.col(value).alias("v")))).alias("c"))
    kind = decided.schema[value].dataType.simpleString()
    whole = F.aggregate("c", F.array().cast(kind), lambda acc, c: F.concat(acc, F.slice(c["v"], F.size(acc) - c["offset"] + 1, F.greatest(F.size(c["v"]) - F.size(acc) + c["offset"], F.lit(0)))))
    return lists.select("doc_id", whole.alias(value))


def once_each(corpus: DataFrame, decide: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Decide each distinct text once and give its copies the same result; digests are shuffled, not texts."""
    digest = F.md5(F.to_json(F.transform("sents", lambda s: s["text"])).cast("binary"))
    ids = corpus.select("doc_id", digest.alias("digest"))
    first = ids.groupBy("digest").agg(F.min("doc_id").alias("first"))
    got = decide(corpus.join(first.select(F.col("first").alias("doc_id")), "doc_id", "left_semi")).withColumnRenamed("doc_id", "first")
    return ids.join(first, "digest").join(got, "first").drop("digest", "first")
