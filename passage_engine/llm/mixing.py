"""Mixing sources to target weights by entropy balancing.

Among all document rates that meet the token constraints, the ones of least relative entropy to the
given rates are exponentially tilted: rate = exp(sum of the multipliers of the constraints that the
document counts in), held to a cap. Newton steps on the convex dual find the multipliers; each step
is an aggregate over strata (the distinct combinations of constraints), so the documents are read
once. Rates become whole copies by error diffusion over documents in the order of their sizes,
in buckets of bounded size, which keeps the tokens taken near the target.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, stored

#: Words for the size of a text.
WORDS = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5.0, 2.0, 1.0)


def shares(sizes: dict, weights: tuple[float, ...] = WEIGHTS, most: float = 3.0) -> dict:
    """Target tokens of each source: sources by code point, null last, weigh ``weights`` in turn and
    share all tokens; a target stops at ``most`` times its source's size and the excess is shared
    again by weight until none is above.
    """
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, open_, out = float(sum(sizes.values())), list(names), {}
    while open_:
        unit = left / sum(weight[s] for s in open_)
        full = [s for s in open_ if weight[s] * unit > most * sizes[s]]
        if not full:
            return out | {s: weight[s] * unit for s in open_}
        for s in full:
            out[s] = most * sizes[s]
            left -= out[s]
        open_ = [s for s in open_ if s not in full]
    return out


def measured(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size) of each document; null text has size 0."""
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), F.coalesce(F.size(F.regexp_extract_all("text", F.lit(WORDS), F.lit(0))).cast("long"), F.lit(0)).alias("size"))


def balance(strata: DataFrame, keys: list[str], targets: list[dict], most: float = 3.0, steps: int = 60, tolerance: float = 1e-9, bound: int = 100_000) -> dict[tuple, float]:
    """Newton iterations on the dual: strata (keys.., tokens) to the multiplier of each (key number, value).

    Each step aggregates over the strata the tokens taken at the present multipliers: that is the
    gradient with the targets, and, without tokens at the cap, the Hessian's diagonal. With one key
    the Hessian is diagonal and this is Newton's method; with several the keys take turns. A target
    at the cap leaves its multiplier at log(most).
    """
    n = sum(map(len, targets))
    if n > bound:
        raise ValueError(f"{n} constraints are more than {bound}")
    spark = strata.sparkSession
    lam = {(k, v): 0.0 for k, t in enumerate(targets) for v in t}
    for step in range(steps):
        now = strata
        for k, key in enumerate(keys):
            table = spark.createDataFrame([(v, lam[k, v]) for v in targets[k]], f"v string, `lam{k}` double")
            now = now.join(F.broadcast(table), now[key].eqNullSafe(table.v), "left").drop("v")
        rate = F.exp(F.least(sum((F.col(f"lam{k}") for k in range(len(keys))), F.lit(0.0)), F.lit(math.log(most))))
        now = now.withColumn("taken", F.col("tokens") * rate)
        worst = 0.0
        k = step % len(keys)
        for r in now.groupBy(keys[k]).agg(F.sum("taken").alias("taken"), F.sum("tokens").alias("tokens")).collect():
            v, goal = r[keys[k]], targets[k].get(r[keys[k]], 0.0)
            if not r.tokens or v not in targets[k]:
                continue
            if goal >= most * r.tokens * (1 - 1e-12) and len(keys) == 1:
                gap, new = abs(lam[k, v] - math.log(most)), math.log(most)
            elif goal <= 0:
                gap, new = 0.0, -700.0
            else:
                gap = abs(r.taken - goal) / goal
                new = lam[k, v] - max(-1.0, min(1.0, (r.taken - goal) / max(r.taken, 1e-300)))  # gradient over Hessian, damped
            worst, lam[k, v] = max(worst, gap), new
        if worst < tolerance and step >= len(keys) - 1:
            break
    return lam


def _rounded(pdf: pd.DataFrame) -> pd.DataFrame:
    """Whole copies of one bucket: the share beyond whole copies is carried from document to document."""
    pdf = pdf.sort_values(["size", "doc_id"], ascending=[False, True], kind="stable", na_position="last")
    rate, acc, copies = float(pdf.rate.iloc[0]), 0.0, []
    whole = math.floor(rate + 1e-9)
    part = max(0.0, rate - whole)
    for size in pdf["size"].tolist():
        acc += part * size
        extra = part > 1e-12 and acc >= size / 2 and size > 0
        acc -= size if extra else 0
        copies.append(whole + int(extra))
    return pdf.assign(copies=copies)[["doc_id", "source", "size", "source_size", "target", "rate", "copies"]]


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = 3.0, bucket_rows: int = 4096) -> DataFrame:
    """Documents (doc_id, text, source) to (doc_id, source, size, source_size, target, rate, copies, taken).

    No document has more than ``most`` copies; the words taken from a source miss its target by
    about the smallest documents of its buckets. A document of size 0 takes nothing; it keeps the
    whole copies of its source's rate. The result depends on the rows alone, not on their
    partitions; repeated rows stay, each with its own copies. Other columns are not read.
    """
    spark = docs.sparkSession
    sizes = stored(measured(docs), "sizes")
    strata = stored(sizes.groupBy("source").agg(F.sum("size").alias("tokens"), F.count("*").alias("rows")), "strata")
    found = {r.source: (r.tokens, r.rows) for r in strata.collect()}
    goals = shares({s: t for s, (t, _) in found.items()}, weights, most)
    lam = balance(strata.select("source", "tokens"), ["source"], [goals], most)
    table = [(s, int(t), float(goals[s]), min(most, math.exp(lam[0, s])), -(-n // bucket_rows)) for s, (t, n) in found.items()]
    sources = spark.createDataFrame(table, "s string, source_size long, target double, rate double, buckets int")
    rows = sizes.join(F.broadcast(sources), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    kind = sizes.schema["doc_id"].dataType.simpleString()
    out = rows.withColumn("bucket", F.pmod(F.xxhash64("doc_id"), F.col("buckets"))).groupBy("source", "bucket").applyInPandas(_rounded, f"doc_id {kind}, source string, size long, source_size long, target double, rate double, copies int")
    return out.withColumn("taken", F.col("copies") * F.col("size"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The rows with all their columns, as often as the mix takes them, numbered by mix_copy from 1.

    Rows of one doc_id are taken by their mean count; what it has beyond a whole number decides by a
    hash of each row's text. Rows without doc_id stay once. Where the rows have a column mix_copy of
    their own, the number's name is lengthened by an underscore.
    """
    name, mean = free_name("mix_copy", docs.columns), free_name("__copies", docs.columns)
    copies = mix(docs, **options).where("doc_id is not null").groupBy("doc_id").agg(F.avg("copies").alias(mean))
    out = docs.join(copies, "doc_id", "left")
    whole = F.floor(mean)
    share = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    n = F.when(F.col("doc_id").isNull(), 1).otherwise(whole + (share < F.col(mean) - whole).cast("int")).cast("int")
    return out.where(n > 0).withColumn(name, F.explode(F.sequence(F.lit(1), n))).drop(mean)
