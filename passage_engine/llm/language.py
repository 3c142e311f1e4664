"""Language identification: multinomial naive Bayes over hashed character n-grams.

Counts come from a sample of bounded size of the labelled rows; the matrix of log-probabilities
(buckets x languages, both bounded by parameters) is broadcast; whole texts are scored in numpy,
many at once: every n-gram's row of the matrix is added up to its text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hash_share, id_crc, runs, texts_of

UNKNOWN = "und"
#: Fixed multipliers, one for each position of an n-gram.
STEPS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], np.uint32)


@dataclass
class LanguageModel:
    langs: list[str]
    logp: np.ndarray  # buckets x languages
    prior: np.ndarray
    orders: tuple[int, ...]


def _codes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the lower-case texts, each closed by a line end, and where each text ends."""
    low = [t.lower() for t in texts]
    joined = "\n".join([*low, ""])
    return np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32), np.cumsum([len(t) + 1 for t in low])


def _buckets(codes: np.ndarray, ends: np.ndarray, n: int, size: int) -> np.ndarray:
    """Bucket of the n-gram that begins at each code point; beyond its text's end it reads line ends."""
    h = np.full(len(codes), n, np.uint32) * np.uint32(0x165667B1)
    for j in range(n):
        c = np.concatenate([codes[j:], np.full(min(j, len(codes)), 10, np.uint32)])
        for t in range(1, j + 1):
            at = ends - t
            c[at[at >= 0]] = 10
        h = (h ^ c) * STEPS[j]
        h ^= h >> np.uint32(15)
    return (h % np.uint32(size)).astype(np.int32)


def in_sample(label: str, shares: dict, key: str) -> Column:
    """Rows of each label up to its share, chosen by the id alone."""
    out = F.lit(False)
    for value, share in shares.items():
        out = F.when(F.col(label) == value, hash_share(key) < share).otherwise(out)
    return out


def fit(labelled: DataFrame, per_lang: int = 2000, buckets: int = 1 << 15, orders: tuple[int, ...] = (1, 2, 3), most_langs: int = 256) -> LanguageModel:
    """Rows (doc_id, text, lang) to a model; about ``per_lang`` rows of each language are read.

    The languages are all non-null labels; more than ``most_langs`` of them raise. No rows: a model
    that knows no language and predicts ``und``.
    """
    rows = labelled.where("lang is not null and doc_id is not null").select("doc_id", "text", "lang")
    sizes = {r.lang: r["count"] for r in rows.groupBy("lang").count().limit(most_langs + 1).collect()}
    if len(sizes) > most_langs:
        raise ValueError(f"more than {most_langs} languages")
    langs = sorted(sizes)
    at = {x: i for i, x in enumerate(langs)}

    def count(batches):
        total = np.zeros((len(langs), buckets), np.int64)
        for b in batches:
            texts, own = texts_of(b), np.array([at[x] for x in b.column("lang").to_pylist()], np.int64)
            for i, j in runs(texts):
                codes, ends = _codes(texts[i:j])
                row = np.repeat(own[i:j], np.diff(ends, prepend=0)) * buckets
                for n in orders:
                    total += np.bincount(row + _buckets(codes, ends, n, buckets), minlength=total.size).reshape(total.shape)
        who, what = np.nonzero(total)
        yield pa.record_batch([pa.array(who.astype(np.int32)), pa.array(what.astype(np.int32)), pa.array(total[who, what])], names=["lang", "bucket", "times"])

    shares = {x: min(1.0, per_lang / sizes[x]) for x in langs}
    counts = np.ones((len(langs), buckets))
    if langs:
        chosen = rows.where(in_sample("lang", shares, "doc_id"))
        got = chosen.select("text", "lang").mapInArrow(count, "lang int, bucket int, times long").groupBy("lang", "bucket").agg(F.sum("times").alias("times")).toPandas()
        counts[got.lang.to_numpy(np.int64), got.bucket.to_numpy(np.int64)] += got.times.to_numpy()
    logp = np.log(counts / counts.sum(axis=1, keepdims=True)).T.astype(np.float32) if langs else np.zeros((buckets, 0), np.float32)
    prior = np.log(np.array([sizes[x] for x in langs], float) / max(1, sum(sizes.values())))
    return LanguageModel(langs, np.ascontiguousarray(logp), prior, orders)


def score_texts(texts: list[str], model: LanguageModel) -> tuple[list[str], np.ndarray]:
    """Language and posterior probability of each text; ``und`` and 0 without a letter."""
    names: list[str] = []
    scores = np.zeros(len(texts))
    for i, j in runs(texts, 1 << 19):
        codes, ends = _codes(texts[i:j])
        starts = np.concatenate([[0], ends[:-1]])
        total = np.zeros((j - i, len(model.langs)))
        for n in model.orders:
            rows = model.logp[_buckets(codes, ends, n, len(model.logp))]
            if model.langs:
                total += np.add.reduceat(rows, starts, axis=0, dtype=np.float64)
        total += model.prior
        for k in range(j - i):
            if not model.langs or not any(map(str.isalpha, texts[i + k])):
                names.append(UNKNOWN)
                continue
            best = int(total[k].argmax())
            names.append(model.langs[best])
            scores[i + k] = 1 / np.exp(total[k] - total[k, best]).sum()
    return names, scores


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, lang_pred, score).

    Null and empty texts and such without a letter give ``und`` with score 0. A tie goes to the
    language that sorts first. Repeated rows stay; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            names, scores = score_texts(texts_of(b), shared.value)
            yield pa.record_batch([b.column("doc_id"), pa.array(names, pa.string()), pa.array(scores)], names=["doc_id", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang_pred string, score double")


def held_out(mod: int, rest: int) -> Column:
    return F.coalesce(id_crc("doc_id") % mod == rest, F.lit(False))
