"""Toxicity by the nearest labelled examples: exact TF-IDF cosine over a block-max inverted index.

Terms are chosen from the labels (all that tell more than chance would), as in whole texts of invented
or rare words all others would drown them. Each labelled text becomes a vector of TF-IDF weights
over these terms and over marks of how many such words it holds; equal vectors share one entry with
their counts of labels. Each term has a posting list of entries and weights, cut where the entries'
blocks change, with the largest weight of each cut: blocks are scored in the order of their bounds
until the k-th best cosine beats the next bound, so the neighbours are exact. Votes weighted by
nearness are calibrated on votes that leave each labelled text out.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, id_crc, stored, texts_of
from .language import in_sample

WORD = re.compile(r"[^\W\d_]+")
#: Pseudo-terms for one, two and at least three chosen words in a text.
MARKS = ("#1", "#2", "#3")


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


@dataclass
class Inverted:
    """Postings sorted by term and entry; a cell is the part of a term's list in one block of entries."""

    blocks: int
    first: np.ndarray  # of each term: its first cell
    block: np.ndarray  # of each cell
    largest: np.ndarray  # weight in each cell
    start: np.ndarray  # of each cell in the postings
    entry: np.ndarray
    weight: np.ndarray

    def cells(self, at: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The cells of the terms' lists, each with its term's weight in the query."""
        n = self.first[at + 1] - self.first[at]
        return _ranges(self.first[at], n), np.repeat(w, n)

    def bounds(self, cells: np.ndarray, w: np.ndarray) -> np.ndarray:
        """An upper bound of the cosine with the entries of each block."""
        return np.bincount(self.block[cells], weights=w * self.largest[cells], minlength=self.blocks)

    def cosines(self, chosen: np.ndarray, size: int, cells: np.ndarray, w: np.ndarray) -> np.ndarray:
        """The cosines with the entries of the chosen blocks: a row of ``size`` for each."""
        place = np.full(self.blocks, -1)
        place[chosen] = np.arange(len(chosen))
        row = place[self.block[cells]]
        cells, w, row = cells[row >= 0], w[row >= 0], row[row >= 0]
        n = self.start[cells + 1] - self.start[cells]
        at = _ranges(self.start[cells], n)
        flat = np.repeat(row, n) * size + self.entry[at] % size
        return np.bincount(flat, weights=np.repeat(w, n) * self.weight[at], minlength=len(chosen) * size).reshape(len(chosen), size)


def _ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The numbers of all ranges, one after another."""
    return np.repeat(starts - np.cumsum(sizes) + sizes, sizes) + np.arange(int(sizes.sum()))


def inverted(vectors: list[tuple[np.ndarray, np.ndarray]], terms: int, block: int) -> Inverted:
    """The index of the entries' (terms, weights), entries numbered as listed."""
    entry = np.repeat(np.arange(len(vectors)), [len(v[0]) for v in vectors]) if vectors else np.zeros(0, np.int64)
    term = np.concatenate([np.zeros(0, np.int64), *(v[0] for v in vectors)])
    weight = np.concatenate([np.zeros(0), *(v[1] for v in vectors)])
    by = np.lexsort((entry, term))
    entry, term, weight = entry[by], term[by], weight[by]
    blocks = -(-len(vectors) // block)
    cell = term * max(1, blocks) + entry // block
    start = np.flatnonzero(np.concatenate([np.ones(min(1, len(cell)), bool), cell[1:] != cell[:-1]]))
    largest = np.maximum.reduceat(weight, start) if len(start) else np.zeros(0)
    return Inverted(blocks, np.searchsorted(term[start], np.arange(terms + 1)), entry[start] // block, largest, np.append(start, len(entry)), entry, weight)


@dataclass
class ToxicityModel:
    terms: dict[str, int]
    idf: np.ndarray
    block: int
    sizes: np.ndarray  # entries x (clean, toxic)
    index: Inverted = field(default_factory=lambda: inverted([], 0, 1))
    k: int = 25
    prior: float = 0.1
    empty: tuple[float, float] = (0.0, 0.0)
    line: tuple[float, float] = (1.0, 0.0)


def vector(text: str, terms: dict[str, int], idf: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """Indices and unit weights; None if the text holds none of the terms."""
    found = Counter(i for w in words_of(text) if (i := terms.get(w)) is not None)
    if not found:
        return None
    mark = min(len(MARKS), sum(found.values()))
    at = np.array([*sorted(found), len(terms) + mark - 1], np.int64)
    tf = np.array([1 + np.log(found[i]) for i in at[:-1].tolist()] + [float(mark)])
    w = tf * idf[at]
    return at, w / np.sqrt((w * w).sum())


def nearest(query: tuple[np.ndarray, np.ndarray], model: ToxicityModel, without: tuple[int, int] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The nearest entries that hold at least k texts, best first, all ties of the last cosine kept: cosines, entries, copies.

    Blocks are scored a few at a time, in the order of their bounds. ``without`` (entry, label)
    leaves one text out.
    """
    cells, w = model.index.cells(*query)
    limit = model.index.bounds(cells, w)
    order = np.argsort(-limit, kind="stable")
    order = order[limit[order] > 0]
    cos, entry, copies = np.zeros(0), np.zeros(0, np.int64), np.zeros(0)
    worst, done, step = 0.0, 0, 8
    while done < len(order) and limit[order[done]] >= worst - 1e-12:
        blocks = order[done : done + step]
        new = model.index.cosines(blocks, model.block, cells, w)
        i, j = np.nonzero(new > max(0.0, worst - 1e-12))
        e = blocks[i] * model.block + j
        n = model.sizes[e].sum(axis=1)
        if without is not None:
            n = n - (e == without[0])
        keep = n > 0
        cos, entry, copies = np.concatenate([cos, new[i, j][keep]]), np.concatenate([entry, e[keep]]), np.concatenate([copies, n[keep]])
        by = np.lexsort((entry, -cos))
        cos, entry, copies = cos[by], entry[by], copies[by]
        at = int(np.searchsorted(np.cumsum(copies), model.k))
        if at < len(cos):
            worst = float(cos[at])
            near = cos >= worst - 1e-12
            cos, entry, copies = cos[near], entry[near], copies[near]
        done, step = done + step, 2 * step
    return cos, entry, copies


def neighbours(query: tuple[np.ndarray, np.ndarray], model: ToxicityModel, without: tuple[int, int] | None = None) -> list[tuple[float, int, float]]:
    """(cosine, entry, copies) of the nearest entries, best first; see ``nearest``."""
    return list(zip(*(x.tolist() for x in nearest(query, model, without)), strict=True))


def vote(query, model: ToxicityModel, without: tuple[int, int] | None = None) -> tuple[float, list]:
    """Share of toxic votes, weighted by nearness and held to the prior by one vote; the three nearest (cosine, entry)."""
    if query is None:
        clean, toxic = model.empty
        if without is not None:
            clean, toxic = clean - (without[1] == 0), toxic - (without[1] == 1)
        return (toxic + model.prior) / (clean + toxic + 1), []
    cos, entry, copies = nearest(query, model, without)
    own = model.sizes[entry, 1]
    if without is not None and without[1] == 1:
        own = own - (entry == without[0])
    return float(((cos * own).sum() + model.prior) / ((cos * copies).sum() + 1)), list(zip(cos[:3].tolist(), entry[:3].tolist(), strict=True))


def fit(docs: DataFrame, labels: DataFrame, mod: int = 3, rest: int = 1, most: int = 20_000, least_texts: int = 3, block: int = 64, k: int = 25) -> ToxicityModel:
    """Documents (doc_id, text) and labels (doc_id, toxic) to a model.

    Rows whose crc32(doc_id as text) mod ``mod`` is ``rest`` are held out. About ``most`` ids of each
    label are used at most, chosen by the id alone: that bounds what is broadcast, the words that can
    be chosen and the index.
    Of several labels of an id the largest counts; null ids and labels don't. Without rows the
    model scores its prior.
    """
    ids = labels.where("toxic in (0, 1) and doc_id is not null").where(id_crc("doc_id") % mod != rest)
    ids = ids.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    sizes = {r.toxic: r["count"] for r in ids.groupBy("toxic").count().collect()}
    n = np.array([sizes.get(0, 0), sizes.get(1, 0)], float)
    ids = ids.where(in_sample("toxic", {y: min(1.0, most / c) for y, c in sizes.items()}, "doc_id"))
    chosen = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id")
    taken = np.minimum(n, most)

    def count(batches):
        seen = [Counter(), Counter()]
        for b in batches:
            for t, y in zip(texts_of(b), b.column("toxic").to_pylist(), strict=True):
                seen[y].update(set(words_of(t)))
        words = [*{*seen[0], *seen[1]}]
        yield pa.record_batch([pa.array(words, pa.string()), pa.array([seen[0][w] for w in words], pa.int64()), pa.array([seen[1][w] for w in words], pa.int64())], names=["word", "clean", "toxic"])

    # Words of toxic texts, by the log-likelihood ratio of their presence against the label; it must
    # exceed what the best of so many words would reach by chance.
    counts = stored(chosen.select("text", "toxic").mapInArrow(count, "word string, clean long, toxic long").groupBy("word").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic")).where(F.col("toxic") >= least_texts), "words")
    base = float(taken[1] / max(1.0, taken.sum()))
    odds = min(max(base, 1e-6), 1 - 1e-6)
    both = F.col("clean") + F.col("toxic")
    g = 2 * (F.col("toxic") * F.log(F.col("toxic") / (both * odds)) + F.when(F.col("clean") > 0, F.col("clean") * F.log(F.col("clean") / (both * (1 - odds)))).otherwise(0.0))
    chance = 2 * np.log(max(1, counts.count()) / 0.1)
    kept = counts.withColumn("g", g).where((F.col("toxic") > 2 * odds * both) & (F.col("g") > float(chance))).select("word", "clean", "toxic").collect()
    index = {r.word: i for i, r in enumerate(sorted(kept, key=lambda r: r.word))}
    total = max(1.0, taken.sum())
    df = np.ones(len(index) + len(MARKS))
    for r in kept:
        df[index[r.word]] = r.clean + r.toxic
    idf = np.log(1 + total / df)
    idf[len(index) :] = idf[: len(index)].mean() / 2 if index else 1.0

    def vectors(batches):
        for b in batches:
            got = [vector(t, index, idf) for t in texts_of(b)]
            blobs = [b"" if v is None else np.concatenate([v[0].astype(np.float64), v[1]]).tobytes() for v in got]
            yield pa.record_batch([pa.array(blobs, pa.binary()), b.column("toxic")], names=["v", "toxic"])

    entries = chosen.select("text", "toxic").mapInArrow(vectors, "v binary, toxic int").groupBy("v").agg(F.sum(1 - F.col("toxic")).alias("clean"), F.sum("toxic").alias("toxic")).orderBy("v").collect()
    model = ToxicityModel(index, idf, block, np.array([[r.clean, r.toxic] for r in entries if len(r.v)], float).reshape(-1, 2), k=k, prior=float(base) if taken.sum() else 0.0)
    model.empty = next(((float(r.clean), float(r.toxic)) for r in entries if not len(r.v)), (0.0, 0.0))
    vs = [np.frombuffer(r.v).reshape(2, -1) for r in entries if len(r.v)]
    # entries of the same leading terms lie in the same blocks, which makes the bounds sharp
    by = sorted(range(len(vs)), key=lambda i: tuple(vs[i][0][np.argsort(-vs[i][1])].tolist()))
    model.sizes = model.sizes[by] if by else model.sizes
    entries = [(vs[i][0].astype(np.int64), vs[i][1]) for i in by]
    model.index = inverted(entries, len(idf), block)
    model.line = _calibrate(model, entries)
    return model


def _calibrate(model: ToxicityModel, entries: list, most: int = 4000) -> tuple[float, float]:
    """Logistic line (slope, offset) from the log-odds of the vote that leaves a text out to its label."""
    xs, ys, ns = [], [], []
    step = max(1, len(entries) // most)
    for e in [*range(0, len(entries), step), None]:
        for y in (0, 1):
            m = model.empty[y] if e is None else model.sizes[e, y]
            if m > 0:
                p = vote(None if e is None else entries[e], model, (-1 if e is None else e, y))[0]
                xs.append(np.log((p + 1e-3) / (1 - p + 1e-3)))
                ys.append(y)
                ns.append(m)
    x, y, w = (np.array(v, float) for v in (xs, ys, ns))
    if not len(x) or not 0 < (y * w).sum() < w.sum():
        return 1.0, 0.0
    a, b = 1.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-(a * x + b)))
        g = np.array([(w * (p - y) * x).sum() + 1e-2 * (a - 1), (w * (p - y)).sum() + 1e-2 * b])
        r = w * p * (1 - p)
        h = np.array([[(r * x * x).sum() + 1e-2, (r * x).sum()], [(r * x).sum(), r.sum() + 1e-2]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-8:
            break
    return (float(a), float(b)) if a > 0 else (1.0, 0.0)


def score_text(text: str, model: ToxicityModel, memo: dict | None = None) -> tuple[float, list]:
    """Calibrated score and the nearest entries (cosine, toxic share) as evidence."""
    v = vector(text, model.terms, model.idf)
    key = None if v is None else (v[0].tobytes(), v[1].tobytes())
    if memo is not None and key in memo:
        return memo[key]
    p, near = vote(v, model)
    x = np.log((p + 1e-3) / (1 - p + 1e-3))
    got = float(1 / (1 + np.exp(-(model.line[0] * x + model.line[1])))), [(round(c, 6), float(model.sizes[e, 1] / model.sizes[e].sum())) for c, e in near]
    if memo is not None:
        if len(memo) > 50_000:
            memo.clear()
        memo[key] = got
    return got


RESULTS = ("score", "predicted", "evidence")


def _run(model, threshold: float, names: list[str]):
    def run(batches):
        memo: dict = {}
        for b in batches:
            got = [score_text(t, model.value, memo) for t in texts_of(b)]
            scores = np.array([g[0] for g in got])
            b = b.append_column(names[0], pa.array(scores, pa.float64()))
            b = b.append_column(names[1], pa.array((scores >= threshold).astype(np.int32)))
            yield b.append_column(names[2], pa.array([";".join(f"{c:.4f}:{t:.3f}" for c, t in g[1]) for g in got], pa.string()))

    return run


def score(docs: DataFrame, model: ToxicityModel, threshold: float = 0.7) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, score, predicted, evidence).

    evidence lists cosine:toxic share of the three nearest entries. Null texts are empty; empty
    texts, and such without a chosen term, get the calibrated vote of the labelled texts that are
    likewise. Repeated rows stay; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()
    out = docs.select("doc_id", "text").mapInArrow(_run(shared, threshold, list(RESULTS)), f"doc_id {kind}, text string, score double, predicted int, evidence string")
    return out.select("doc_id", *RESULTS)


def reject(docs: DataFrame, model: ToxicityModel, threshold: float = 0.7) -> DataFrame:
    """The rows, with all their columns, whose text scores below the threshold; columns may have any names."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = [free_name(f"__{x}", docs.columns) for x in RESULTS]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema), *(f"`{x}` {kind}" for x, kind in zip(names, ("double", "int", "string"), strict=True))])
    return docs.mapInArrow(_run(shared, threshold, names), schema).where(F.col(f"`{names[1]}`") == 0).drop(*names)
