"""Scorers without training, as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.text import words


def cue_prob(s: Column) -> Column:
    """Context-free cue: 1 / (1 + (length + idx) mod 7); exactly 0.5 for remainder 1."""
    return 1.0 / (1 + (F.length(s["text"]) + s["idx"]) % 7)


def cue_positive(s: Column) -> Column:
    """Strictly more than 0.5."""
    return cue_prob(s) > 0.5


def is_positive(prob: Column, threshold: float = 0.5) -> Column:
    """Null and NaN are negative; Spark would order NaN above every number."""
    return F.coalesce(prob.isNotNull() & ~F.isnan(prob) & (prob > threshold), F.lit(False))


def cohesion(sents: Column, k: int = 3) -> Column:
    """For each sentence, 1 - overlap of the words of the k sentences up to it and of the k after it."""
    sets = F.transform(sents, lambda s: words(s["text"]))

    def at(ws: Column) -> Column:
        def one(_: Column, i: Column) -> Column:
            left = F.array_distinct(F.flatten(F.slice(ws, F.greatest(i - k + 2, F.lit(1)), F.least(i + 1, F.lit(k)))))
            right = F.array_distinct(F.flatten(F.slice(ws, i + 2, k)))
            both = F.size(F.array_union(left, right))
            return F.when(both == 0, 1.0).otherwise(F.round(1 - F.size(F.array_intersect(left, right)) / both, 6))

        return F.transform(ws, one)

    return F.transform(F.array(sets), at)[0]


def cohesion_prob(sents: Column, k: int = 3, c: float = 0.5) -> Column:
    """Logistic of the dissimilarity's excess over mean + c * deviation of the document."""

    def to_prob(d: Column) -> Column:
        n = F.size(d)
        mean = F.aggregate(d, F.lit(0.0), lambda a, x: a + x) / n
        dev = F.sqrt(F.aggregate(d, F.lit(0.0), lambda a, x: a + x * x) / n - mean * mean + 1e-12)
        return F.transform(d, lambda x: 1 / (1 + F.exp(-(x - mean - c * dev) / (dev + 1e-9))))

    return F.transform(F.array(cohesion(sents, k)), to_prob)[0]


def cohesion_positive(sents: Column, k: int = 3, c: float = 0.5) -> Column:
    return F.transform(cohesion_prob(sents, k, c), lambda p: p > 0.5)
