"""Benchmark decontamination: one Aho-Corasick automaton over the windows of normalised benchmark texts.

Texts are normalised to lower-case words with one space between; patterns are windows with a space
on either side, so matches begin and end at words. Every document is scanned once; the word
intervals found are mapped back to code points of the original text.
"""

from __future__ import annotations

import re
from collections import defaultdict
from hashlib import sha256

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import texts_of

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
OTHER = re.compile(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text: str) -> str:
    """Lower-case A-Z only; the number of code points stays."""
    return text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")


def normal(text: str) -> str:
    """Words with a space before, between and after; one space if there are none."""
    words = OTHER.sub(" ", lower(text)).strip(" ")
    return f" {words} " if words else " "


def windows(items: list[tuple], width: int = 10) -> dict[str, set]:
    """Pattern to the item_ids that have it; an item of fewer words, but not none, is one window."""
    out: dict[str, set] = defaultdict(set)
    for item, text in items:
        w = normal(text or "").split()
        for i in range(max(1, len(w) - width + 1) if w else 0):
            out[f" {' '.join(w[i : i + width])} "].add(item)
    return dict(out)


class Automaton:
    """Built once in each Python worker from the broadcast windows."""

    def __init__(self, patterns: dict[str, set]):
        self.patterns, self.trie = patterns, None

    def __getstate__(self):
        return self.patterns

    def __setstate__(self, patterns):
        self.__init__(patterns)

    def ready(self):
        if self.trie is None and self.patterns:
            self.trie = ahocorasick.Automaton()
            for p, items in self.patterns.items():
                self.trie.add_word(p, (len(p), p.count(" ") - 1, tuple(items)))
            self.trie.make_automaton()
        return self.trie

    def scan(self, text: str) -> tuple[int, list[tuple[int, int]], set]:
        """Number of words, merged intervals of hit words (end exclusive), items found."""
        body = normal(text)
        n = body.count(" ") - 1
        found, items = [], set()
        if self.ready() is not None and n > 0:
            at, seen = 0, 0
            for end, (_, width, ids) in self.trie.iter(body):
                seen += body.count(" ", at, end + 1)
                at = end + 1
                last = seen - 1  # words that end before this space
                found.append((last - width, last))
                items.update(ids)
        merged: list[tuple[int, int]] = []
        for s, e in sorted(found):
            if merged and s <= merged[-1][1]:
                merged[-1] = (merged[-1][0], max(e, merged[-1][1]))
            else:
                merged.append((s, e))
        return max(0, n), merged, items


def offsets(text: str, hits: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Word intervals to intervals of code points of the original text."""
    if not hits:
        return []
    spans = [m.span() for m in WORD.finditer(lower(text))]
    return [(spans[s][0], spans[e - 1][1]) for s, e in hits]


def load(benchmark: DataFrame, width: int = 10, most_chars: int = 20_000_000) -> Automaton:
    """Benchmark (item_id, text) to an automaton; null texts have no window.

    The automaton is broadcast, so the benchmark's size is checked first: beyond ``most_chars``
    code points this raises, and the benchmark is to be scanned in parts (one ``hits`` each, then
    ``union`` and one group by doc_id).
    """
    size = benchmark.agg(F.sum(F.length("text"))).first()[0] or 0
    if size > most_chars:
        raise ValueError(f"a benchmark of {size} characters doesn't fit one automaton of {most_chars}; scan it in parts")
    return Automaton(windows([(r.item_id, r.text) for r in benchmark.select("item_id", "text").collect()], width))


def hits(docs: DataFrame, automaton: Automaton) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, n_words, n_hit, n_items, items_sha256, contaminated, spans).

    spans lists start:end of hit passages in code points of the original. Null text has no words.
    Item ids are compared as strings; a null id counts as ``null``. Repeated rows stay; other
    columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(automaton)

    def run(batches):
        for b in batches:
            texts = texts_of(b)
            got = [shared.value.scan(t) for t in texts]
            names = [sorted("null" if i is None else str(i) for i in items) for _, _, items in got]
            n_hit = [sum(e - s for s, e in h) for _, h, _ in got]
            yield pa.record_batch(
                [b.column("doc_id"), pa.array([n for n, _, _ in got], pa.int64()), pa.array(n_hit, pa.int64()), pa.array([len(x) for x in names], pa.int64()), pa.array([sha256(",".join(x).encode()).hexdigest() for x in names], pa.string()), pa.array([n > 0 for n in n_hit], pa.bool_()), pa.array([",".join(f"{s}:{e}" for s, e in offsets(t, h)) for t, (_, h, _) in zip(texts, got, strict=True)], pa.string())],
                names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "spans"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, spans string")


def clean(docs: DataFrame, automaton: Automaton) -> DataFrame:
    """The rows, with all their columns, that hold no window of the benchmark."""
    shared = docs.sparkSession.sparkContext.broadcast(automaton)

    def run(batches):
        for b in batches:
            yield b.filter(pa.array([not shared.value.scan(t)[1] for t in texts_of(b)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
