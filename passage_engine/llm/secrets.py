"""Secret scans: fixed patterns, and character Markov models of random strings and ordinary identifiers.

The patterns give the base spans. Every other run of 16 or more key-like characters is judged by the
log-likelihood ratio of two first-order Markov models, one trained on random strings (drawn by a
seed, and the secret values that the patterns find in a bounded sample), one on the ordinary words
of that sample.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hash_share, texts_of

#: Fixed patterns, in the order in which kinds are listed.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{16,}")
KINDS = ("assign", "access", "hex", "markov")
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
PLACE = {c: i + 1 for i, c in enumerate(ALPHABET)}
SIZE = len(ALPHABET) + 1

Span = tuple[str, int, int]


def base_spans(text: str) -> list[Span]:
    """Spans of the fixed patterns, by start, then kind as listed; code points, end exclusive."""
    out = [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    out += [("hex", *m.span()) for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0])))


@dataclass
class SecretModel:
    ratio: np.ndarray  # log of random over ordinary, from x to
    threshold: float = 1.0  # nats for each character


def transitions(words: list[str]) -> np.ndarray:
    """Counts of character pairs; 0 stands before the first character and for any other one."""
    out = np.zeros((SIZE, SIZE))
    for w in words:
        at = [0, *(PLACE.get(c, 0) for c in w)]
        np.add.at(out, (at[:-1], at[1:]), 1)
    return out


def random_strings(n: int = 2000, seed: int = 7) -> list[str]:
    """Labelled examples of the random class: base-64, base-36 and hexadecimal strings."""
    rng = np.random.default_rng(seed)
    sets = [ALPHABET[:64], ALPHABET[26:62], ALPHABET[:26] + ALPHABET[52:62], "0123456789abcdef"]
    return ["".join(rng.choice(list(sets[i % len(sets)]), int(rng.integers(16, 48)))) for i in range(n)]


def fit(docs: DataFrame, most_docs: int = 2000, threshold: float = 1.0) -> SecretModel:
    """Train on labelled samples from about ``most_docs`` documents, chosen by doc_id.

    Ordinary: words of letters, digits and joiners outside the base spans. Random: drawn strings
    and the values of the base spans. An empty table trains on the drawn strings alone.
    """
    rows = docs.where("doc_id is not null").select("doc_id", "text")
    n = rows.select("doc_id").count()
    chosen = rows.where(hash_share("doc_id") < min(1.0, most_docs / max(1, n)))

    def count(batches):
        ordinary: Counter = Counter()
        found: Counter = Counter()
        for b in batches:
            for t in texts_of(b):
                end = 0
                for _, s, e in [*base_spans(t), ("", len(t), len(t))]:
                    if s >= end:
                        ordinary.update(re.findall(r"[A-Za-z0-9+/_=-]+", t[end:s]))
                    end = max(end, e)
                found.update(m for k, s, e in base_spans(t) if k != "assign" for m in [t[s:e]])
        for label, words in ((0, ordinary), (1, found)):
            m = transitions(list(words))
            a, c = np.nonzero(m)
            yield pa.record_batch([pa.array(np.full(len(a), label, np.int32)), pa.array(a.astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(m[a, c])], names=["label", "a", "b", "n"])

    got = chosen.select("text").mapInArrow(count, "label int, a int, b int, n double").groupBy("label", "a", "b").agg(F.sum("n").alias("n")).toPandas()
    counts = np.full((2, SIZE, SIZE), 0.5)
    counts[got.label.to_numpy(int), got.a.to_numpy(int), got.b.to_numpy(int)] += got.n.to_numpy(float)
    counts[1] += transitions(random_strings())
    logp = np.log(counts / counts.sum(axis=2, keepdims=True))
    return SecretModel(logp[1] - logp[0], threshold)


def ratio(word: str, model: SecretModel) -> float:
    at = [0, *(PLACE.get(c, 0) for c in word)]
    return float(model.ratio[at[:-1], at[1:]].sum()) / max(1, len(word))


def spans_of(text: str, model: SecretModel) -> tuple[list[Span], list[Span]]:
    """Base spans, and all spans with those that the models add outside them."""
    base = base_spans(text)
    more = []
    for m in CANDIDATE.finditer(text):
        s, e = m.span()
        if not any(a < e and s < b for _, a, b in base) and ratio(m[0], model) > model.threshold:
            more.append(("markov", s, e))
    return base, sorted(base + more, key=lambda s: (s[1], KINDS.index(s[0])))


def listed(spans: list[Span]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def scan(docs: DataFrame, model: SecretModel) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, n_assign, n_access, n_hex, base_sha256, spans).

    Null text is empty and has no spans. Repeated rows stay; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            found = [spans_of(t, shared.value) for t in texts_of(b)]
            kinds = [Counter(k for k, _, _ in base) for base, _ in found]
            yield pa.record_batch(
                [b.column("doc_id"), *(pa.array([c[k] for c in kinds], pa.int64()) for k in KINDS[:3]), pa.array([sha256(listed(base).encode()).hexdigest() for base, _ in found], pa.string()), pa.array([listed(every) for _, every in found], pa.string())],
                names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact_text(text: str, spans: list[Span], mark: str = "[secret]") -> str:
    out, end = [], 0
    for _, s, e in spans:
        if e <= end:
            continue
        if s >= end:
            out += [text[end:s], mark]
        end = e
    return "".join([*out, text[end:]])


def redact(docs: DataFrame, model: SecretModel) -> DataFrame:
    """The same rows and columns; every span in ``text`` gives way to a mark, and n_chars follows if it is there.

    Null text stays null.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            texts = b.column("text").to_pylist()
            new = [t if t is None or not (s := spans_of(t, shared.value)[1]) else redact_text(t, s) for t in texts]
            cols = dict(zip(b.schema.names, b.columns, strict=True)) | {"text": pa.array(new, pa.string())}
            if "n_chars" in cols:
                cols["n_chars"] = pa.array([x if o == t else len(t) for o, t, x in zip(texts, new, cols["n_chars"].to_pylist(), strict=True)], cols["n_chars"].type)
            yield pa.RecordBatch.from_arrays(list(cols.values()), names=list(cols))

    return docs.mapInArrow(run, docs.schema)
