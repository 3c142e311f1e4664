"""Accuracy and cost measures, each one scan and one shuffle of partial aggregates."""

from __future__ import annotations

import math
import os

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as t


def counts(pred: Column, ref: Column, scored: Column | None = None) -> list[Column]:
    on = F.lit(True) if scored is None else scored
    return [F.coalesce(F.sum((pred & ref & on).cast("long")), F.lit(0)).alias("tp"), F.coalesce(F.sum((pred & ~ref & on).cast("long")), F.lit(0)).alias("fp"), F.coalesce(F.sum((~pred & ref & on).cast("long")), F.lit(0)).alias("fn")]


def with_prf(df: DataFrame) -> DataFrame:
    """Adds p, r, f1 to tp, fp, fn; parts without cases are 0."""
    p = F.when(F.col("tp") + F.col("fp") > 0, F.col("tp") / (F.col("tp") + F.col("fp"))).otherwise(0.0)
    r = F.when(F.col("tp") + F.col("fn") > 0, F.col("tp") / (F.col("tp") + F.col("fn"))).otherwise(0.0)
    f1 = F.when(2 * F.col("tp") + F.col("fp") + F.col("fn") > 0, 2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))).otherwise(0.0)
    return df.withColumns({"p": F.round(p, 6), "r": F.round(r, 6), "f1": F.round(f1, 6)})


def prf(rows: DataFrame, *by: str) -> DataFrame:
    """Positive precision, recall and F1 of sentence rows (idx, n_sent, is_boundary, ends_para).

    The last sentence of every document is left out.
    """
    scored = F.col("idx") < F.col("n_sent") - 1
    return with_prf(rows.groupBy(*by).agg(*counts(F.col("is_boundary"), F.col("ends_para"), scored)))


def array_counts(pred: Column, ref: Column) -> Column:
    """(tp, fp, fn) of one document from its two arrays, without the last sentence; no explode."""
    n = F.greatest(F.size(ref) - 1, F.lit(0))
    both = F.arrays_zip(F.slice(pred, 1, n).alias("p"), F.slice(ref, 1, n).alias("r"))
    count = lambda f: F.size(F.filter(both, f)).cast("long")
    return F.struct(count(lambda x: x["p"] & x["r"]).alias("tp"), count(lambda x: x["p"] & ~x["r"]).alias("fp"), count(lambda x: ~x["p"] & x["r"]).alias("fn"))


def document_prf(df: DataFrame, pred: str, ref: str, *by: str) -> DataFrame:
    rows = df.select(*by, array_counts(F.col(pred), F.col(ref)).alias("c"))
    return with_prf(rows.groupBy(*by).agg(F.coalesce(F.sum("c.tp"), F.lit(0)).alias("tp"), F.coalesce(F.sum("c.fp"), F.lit(0)).alias("fp"), F.coalesce(F.sum("c.fn"), F.lit(0)).alias("fn")))


def macro(df: DataFrame, pred: str, ref: str, *by: str) -> DataFrame:
    """Mean over documents of their own F1 (the other reading of the average)."""
    each = with_prf(df.select(*by, array_counts(F.col(pred), F.col(ref)).alias("c")).select(*by, "c.*"))
    return each.groupBy(*by).agg(F.round(F.avg("p"), 6).alias("p"), F.round(F.avg("r"), 6).alias("r"), F.round(F.avg("f1"), 6).alias("f1"))


def gain(scores: DataFrame, new: str, old: str, *by: str) -> DataFrame:
    """F1 gain in points of model ``new`` over ``old``."""
    f1 = lambda m: F.max(F.when(F.col("model") == m, F.col("f1")))
    return scores.groupBy(*by).agg(F.round(100 * (f1(new) - f1(old)), 4).alias("gain"))


def pk(pred: Column, ref: Column, k: int) -> Column:
    """Share of sentence pairs k apart on which the two segmentations disagree about 'same segment'."""
    n = F.size(ref)
    starts = F.when(n > k, F.sequence(F.lit(0), n - k - 1)).otherwise(F.array().cast("array<int>"))
    inside = lambda a, i: F.exists(F.slice(a, i + 1, k), lambda x: x)
    wrong = F.filter(starts, lambda i: inside(pred, i) != inside(ref, i))
    return F.when(F.size(starts) > 0, F.size(wrong) / F.size(starts)).otherwise(0.0)


def window_diff(pred: Column, ref: Column, k: int) -> Column:
    """Like pk, with the numbers of boundaries compared."""
    n = F.size(ref)
    starts = F.when(n > k, F.sequence(F.lit(0), n - k - 1)).otherwise(F.array().cast("array<int>"))
    inside = lambda a, i: F.size(F.filter(F.slice(a, i + 1, k), lambda x: x))
    wrong = F.filter(starts, lambda i: inside(pred, i) != inside(ref, i))
    return F.when(F.size(starts) > 0, F.size(wrong) / F.size(starts)).otherwise(0.0)


def mcnemar(df: DataFrame, a: str, b: str, ref: str) -> DataFrame:
    """Continuity-corrected statistic from the two discordant counts."""
    one = F.sum(((F.col(a) == F.col(ref)) & (F.col(b) != F.col(ref))).cast("long"))
    two = F.sum(((F.col(a) != F.col(ref)) & (F.col(b) == F.col(ref))).cast("long"))
    x = df.agg(F.coalesce(one, F.lit(0)).alias("b"), F.coalesce(two, F.lit(0)).alias("c"))
    gap = F.greatest(F.abs(F.col("b") - F.col("c")) - 1, F.lit(0))
    return x.withColumn("chi2", F.when(F.col("b") + F.col("c") > 0, F.round(gap * gap / (F.col("b") + F.col("c")), 6)).otherwise(0.0))


def chi2_p(chi2: float) -> float:
    """Upper tail for one degree of freedom."""
    return math.erfc(math.sqrt(max(chi2, 0.0) / 2))


def randomization(docs: DataFrame, rounds: int = 2000, buckets: int | None = None) -> DataFrame:
    """Paired test by document: (doc_id, tp_a, fp_a, fn_a, tp_b, fp_b, fn_b) to observed, at_least, p.

    Seed s swaps a document's two systems when the first hexadecimal digit of md5(doc-s) is below 8.
    ``buckets`` swaps hashed groups of documents instead, so the rows times seeds stay bounded.
    """
    spark = docs.sparkSession
    cols = ["tp_a", "fp_a", "fn_a", "tp_b", "fp_b", "fn_b"]
    unit = F.col("doc_id") if buckets is None else F.pmod(t.h(F.col("doc_id")), F.lit(buckets))
    units = docs.groupBy(unit.alias("unit")).agg(*(F.sum(c).alias(c) for c in cols))
    seeds = spark.range(rounds).select(F.col("id").alias("seed"))
    f1 = lambda x: F.when(2 * F.sum(f"tp_{x}") + F.sum(f"fp_{x}") + F.sum(f"fn_{x}") > 0, 2 * F.sum(f"tp_{x}") / (2 * F.sum(f"tp_{x}") + F.sum(f"fp_{x}") + F.sum(f"fn_{x}"))).otherwise(0.0)
    observed = units.agg(F.round(F.abs(f1("a") - f1("b")), 9).alias("observed"))
    swap = F.substring(F.md5(t.key(F.col("unit"), F.col("seed")).cast("binary")), 1, 1) < "8"
    mixed = units.crossJoin(F.broadcast(seeds)).select("seed", *(F.when(swap, F.col(c[:-1] + ("b" if c[-1] == "a" else "a"))).otherwise(F.col(c)).alias(c) for c in cols))
    each = mixed.groupBy("seed").agg(F.round(F.abs(f1("a") - f1("b")), 9).alias("d"))
    return each.crossJoin(F.broadcast(observed)).groupBy("observed").agg(F.sum((F.col("d") >= F.col("observed")).cast("long")).alias("at_least"), F.count("*").alias("rounds")).select("observed", "at_least", F.round((1 + F.col("at_least")) / (F.col("rounds") + 1), 6).alias("p"))


def bootstrap(docs: DataFrame, rounds: int = 1000) -> DataFrame:
    """Share of resamples in which system a isn't better: each document weighs a Poisson(1) number by its hash."""
    spark = docs.sparkSession
    cols = ["tp_a", "fp_a", "fn_a", "tp_b", "fp_b", "fn_b"]
    u = F.pmod(t.h(t.key(F.col("doc_id"), F.col("seed"))), F.lit(1 << 20)) / float(1 << 20)
    steps, total = [], 0.0
    for k in range(8):
        total += math.exp(-1) / math.factorial(k)
        steps.append(total)
    w = sum(((u >= s).cast("int") for s in steps), F.lit(0))
    mixed = docs.crossJoin(F.broadcast(spark.range(rounds).select(F.col("id").alias("seed")))).withColumn("w", w)
    f1 = lambda x: 2 * F.sum(F.col("w") * F.col(f"tp_{x}")) / F.greatest(F.sum(F.col("w") * (2 * F.col(f"tp_{x}") + F.col(f"fp_{x}") + F.col(f"fn_{x}"))), F.lit(1))
    each = mixed.select("seed", "w", *cols).groupBy("seed").agg((f1("a") - f1("b")).alias("d"))
    return each.agg(F.round(F.avg((F.col("d") <= 0).cast("double")), 6).alias("p"), F.round(F.avg("d"), 6).alias("gain"))


def cer(rows: DataFrame, *by: str) -> DataFrame:
    """Character error rate: edits over reference characters, measured sentence by sentence."""
    return rows.groupBy(*by).agg(F.sum(F.levenshtein("ref", "hyp").cast("long")).alias("edits"), F.sum(F.length("ref").cast("long")).alias("chars")).withColumn("cer", F.round(F.col("edits") / F.col("chars"), 6))


def work(df: DataFrame, *by: str, wins: str = "wins") -> DataFrame:
    """Passes, sentences encoded and encoded again: the cost that no machine's noise moves."""
    size = F.aggregate(wins, F.lit(0).cast("long"), lambda a, w: a + w["last"] - w["first"] + 1)
    rows = df.select(*by, "n_sent", F.size(wins).cast("long").alias("k"), size.alias("s"))
    return rows.groupBy(*by).agg(F.count("*").alias("docs"), F.coalesce(F.sum("k"), F.lit(0)).alias("passes"), F.coalesce(F.sum("s"), F.lit(0)).alias("sents_encoded"), F.coalesce(F.sum(F.col("s") - F.col("n_sent")), F.lit(0)).alias("sents_repeated"))


def flops(tokens: Column, layers: Column | int, width: Column | int) -> Column:
    """Arithmetic of one pass over so many tokens."""
    return layers * (24.0 * tokens * width * width + 4.0 * tokens * tokens * width)


def time_per_doc(rows: DataFrame, *by: str) -> DataFrame:
    """Mean milliseconds a document from the measured column ``nanos``."""
    return rows.groupBy(*by).agg(F.round(F.avg("nanos") / 1e6, 3).alias("ms"))


def speedup(new: Column | float, old: Column | float):
    """1 - new/old; the time ratio is new/old."""
    return 1 - new / old


def environment(spark: SparkSession) -> dict:
    conf = spark.sparkContext.getConf()
    return {"master": conf.get("spark.master"), "cores": spark.sparkContext.defaultParallelism, "omp": os.environ.get("OMP_NUM_THREADS", "")}


def describe(corpora: DataFrame, *by: str) -> DataFrame:
    """docs, sentences a document, words a sentence, paragraphs a document, sentences a paragraph.

    One pass over document rows: nothing is exploded.
    """
    toks = F.aggregate("sents", F.lit(0).cast("long"), lambda a, s: a + s["n_tok"])
    paras = F.size(F.filter("sents", lambda s: s["ends_para"])).cast("long")
    rows = corpora.where("n_sent > 0").select(*by, F.col("n_sent").cast("long").alias("s"), toks.alias("w"), paras.alias("p"))
    return rows.groupBy(*by).agg(F.count("*").alias("docs"), F.round(F.sum("s") / F.count("*"), 4).alias("s_per_doc"), F.round(F.sum("w") / F.sum("s"), 4).alias("slen"), F.round(F.sum("p") / F.count("*"), 4).alias("p_per_doc"), F.round(F.sum("s") / F.sum("p"), 4).alias("s_per_p"))
