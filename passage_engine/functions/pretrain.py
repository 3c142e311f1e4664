"""Pre-training objectives as generators of training rows.

Rates and span sizes aren't given where the objectives are named; the defaults are the common ones
of published work.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import text as t


def _neighbour_pairs(corpus: DataFrame) -> DataFrame:
    """(doc_id, i, s1, s2) for each sentence and the next."""
    at = F.when(F.col("n_sent") > 1, F.sequence(F.lit(0), F.col("n_sent") - 2)).otherwise(F.array().cast("array<int>"))
    return corpus.select("doc_id", F.inline(F.transform(at, lambda i: F.struct(i.alias("i"), F.get("sents", i)["text"].alias("s1"), F.get("sents", i + 1)["text"].alias("s2")))))


def _others(corpus: DataFrame, n: int = 4096) -> DataFrame:
    """(docs, others): a drawn sentence of each of at most n drawn documents, in the order of a hash.

    The one row is bounded by n; places in it are dense, however few documents there are.
    """
    drawn = F.md5(t.key(F.col("doc_id"), "other").cast("binary"))
    one = F.get("sents", (t.h(t.key(F.col("doc_id"), "sentence")) % F.col("n_sent")).cast("int"))["text"]
    rows = corpus.where("n_sent > 0").select(drawn.alias("o"), "doc_id", one.alias("text")).orderBy("o", "doc_id").limit(n)
    lists = rows.agg(F.array_sort(F.collect_list(F.struct("o", "doc_id", "text"))).alias("x"))
    return lists.select(F.transform("x", lambda v: v["doc_id"]).alias("docs"), F.transform("x", lambda v: v["text"]).alias("others"))


def _with_other(pairs: DataFrame, corpus: DataFrame, n: int = 4096) -> DataFrame:
    """Adds a sentence of another document by a hashed place; pairs without another document go."""
    rows = pairs.crossJoin(F.broadcast(_others(corpus, n)))
    size = F.size("docs")
    at = (t.h(t.key(F.col("doc_id"), F.col("i"), "slot")) % size).cast("int")
    own = F.get("docs", at) == F.col("doc_id")
    return rows.where((size > 1) | (F.get("docs", F.lit(0)) != F.col("doc_id"))).withColumn("other", F.get("others", F.when(own, (at + 1) % size).otherwise(at))).drop("docs", "others")


def next_pairs(corpus: DataFrame) -> DataFrame:
    """(s1, s2, y): y = 1 for contiguous sentences; else s2 comes from elsewhere."""
    p = _with_other(_neighbour_pairs(corpus), corpus)
    y = t.h(t.key(F.col("doc_id"), F.col("i"), "next")) % 2 == 0
    return p.select("doc_id", "i", "s1", F.when(y, F.col("s2")).otherwise(F.col("other")).alias("s2"), y.cast("int").alias("y"))


def order_triples(corpus: DataFrame) -> DataFrame:
    """(s1, s2, y): 0 s1 precedes, 1 s1 follows, 2 the two don't belong together."""
    p = _with_other(_neighbour_pairs(corpus), corpus)
    y = (t.h(t.key(F.col("doc_id"), F.col("i"), "order")) % 3).cast("int")
    return p.select("doc_id", "i", F.when(y == 1, F.col("s2")).otherwise(F.col("s1")).alias("s1"), F.when(y == 1, F.col("s1")).when(y == 2, F.col("other")).otherwise(F.col("s2")).alias("s2"), y.alias("y"))


def span_order(corpus: DataFrame, max_gap: int = 3) -> DataFrame:
    """(s1, s2, y) for sentences with 1 to max_gap - 1 between them: y = 1 if they are swapped."""
    at = F.flatten(F.transform(F.sequence(F.lit(2), F.lit(max_gap)), lambda g: F.transform(F.filter(F.sequence(F.lit(0), F.greatest(F.col("n_sent") - 1, F.lit(0))), lambda i: i + g < F.col("n_sent")), lambda i: F.struct(i.alias("i"), (i + g).alias("j")))))
    rows = corpus.select("doc_id", "sents", F.inline(at))
    y = (t.h(F.concat_ws("-", F.col("doc_id").cast("string"), F.col("i").cast("string"), F.col("j").cast("string"), F.lit("s"))) % 2).cast("int")
    a, b = F.get("sents", F.col("i"))["text"], F.get("sents", F.col("j"))["text"]
    return rows.select("doc_id", "i", "j", F.when(y == 1, b).otherwise(a).alias("s1"), F.when(y == 1, a).otherwise(b).alias("s2"), y.alias("y"))


def _tokens(corpus: DataFrame) -> DataFrame:
    return corpus.select("doc_id", F.inline("sents")).select("doc_id", "idx", F.split("text", t.SPACE).alias("w"))


def _drawn(i: Column, rate: float, what: str) -> Column:
    return t.h(t.key(F.col("doc_id"), F.col("idx"), i, what)) % 1000 < int(rate * 1000)


def word_order(corpus: DataFrame, span: int = 3, rate: float = 0.05) -> DataFrame:
    """Some spans of tokens are reversed; y holds 1 at their places."""
    rows = _tokens(corpus)
    hit = lambda i: _drawn(F.floor(i / span), rate * span, "shuffle") & (F.floor(i / span) * span + span <= F.size("w"))
    x = F.transform("w", lambda v, i: F.when(hit(i), F.get("w", (F.floor(i / span) * 2 * span + span - 1 - i).cast("int"))).otherwise(v))
    return rows.select("doc_id", "idx", x.alias("x"), F.col("w").alias("target"), F.transform("w", lambda v, i: hit(i).cast("int")).alias("y"))


def mask_tokens(corpus: DataFrame, rate: float = 0.15) -> DataFrame:
    """Drawn tokens become a mask; y holds 1 there."""
    rows = _tokens(corpus)
    x = F.transform("w", lambda v, i: F.when(_drawn(i, rate, "mask"), F.lit("[mask]")).otherwise(v))
    return rows.select("doc_id", "idx", x.alias("x"), F.col("w").alias("target"), F.transform("w", lambda v, i: _drawn(i, rate, "mask").cast("int")).alias("y"))


def counted_words(corpus: DataFrame) -> DataFrame:
    """(word, n) of the corpus; words meet by partial aggregation."""
    return _tokens(corpus).select(F.explode("w").alias("word")).groupBy("word").agg(F.count("*").alias("n"))


def replace_tokens(corpus: DataFrame, vocabulary: DataFrame, rate: float = 0.15, most: int = 4096) -> DataFrame:
    """Drawn tokens give way to words of a sampler; y holds 1 where the word changed.

    The sampler draws from the ``most`` commonest words of ``vocabulary`` (word, and n where counted),
    in proportion to n: it stands for the small generator that proposes likely words.
    """
    counted = vocabulary if "n" in vocabulary.columns else vocabulary.withColumn("n", F.lit(1).cast("long"))
    top = counted.orderBy(F.desc("n"), F.md5(F.col("word").cast("binary"))).limit(most)
    pool = top.agg(F.array_sort(F.collect_list(F.struct(F.col("word"), F.col("n").cast("long").alias("n")))).alias("pool"))
    upto = F.aggregate("pool", F.struct(F.lit(0).cast("long").alias("total"), F.array().cast("array<bigint>").alias("sums")), lambda a, x: F.struct((a["total"] + x["n"]).alias("total"), F.concat(a["sums"], F.array(a["total"] + x["n"])).alias("sums")))
    pool = pool.select(F.transform("pool", lambda x: x["word"]).alias("pool"), upto.alias("upto")).select("pool", F.col("upto.total").alias("total"), F.col("upto.sums").alias("sums"))
    rows = _tokens(corpus).crossJoin(F.broadcast(pool))

    halves = F.array(*(F.lit(1 << k) for k in reversed(range(max(most, 1).bit_length()))))

    def other(i: Column) -> Column:
        """The first word whose running total is above the drawn point: the point once, then a bisection."""
        point = t.h(t.key(F.col("doc_id"), F.col("idx"), i, "word")) % F.greatest(F.col("total"), F.lit(1))
        place = lambda u: F.aggregate(halves, F.lit(0), lambda at, b: F.when(F.get("sums", at + b - 1) <= u, at + b).otherwise(at))
        return F.get("pool", F.transform(F.array(point), place)[0])

    x = F.transform("w", lambda v, i: F.when(_drawn(i, rate, "replace"), F.coalesce(other(i), v)).otherwise(v))
    rows = rows.withColumn("x", x)
    return rows.select("doc_id", "idx", "x", F.col("w").alias("target"), F.transform(F.arrays_zip(F.col("x").alias("a"), F.col("w").alias("b")), lambda z: (z["a"] != z["b"]).cast("int")).alias("y"))
