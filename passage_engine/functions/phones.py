"""Pronunciations: rule-based lexicon, recognition noise, phone vectors in SQL terms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import text as t

#: Fixed rules, applied in this order.
ACCENTS = ("àâäáãåçéèêëíìîïñóòôöõúùûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy")
DIGRAPHS = (("ß", "s"), ("sch", "X"), ("eau", "o"), ("sh", "X"), ("ch", "X"), ("th", "T"), ("wh", "v"), ("ph", "f"), ("qu", "k"), ("ck", "k"), ("tz", "s"), ("ou", "u"))
MERGED = ("pdgcqzvwjx", "btkkksffik")
SYMBOLS = "abcdefghijklmnopqrstuvwxyzXT"


def fold(x: Column) -> Column:
    return F.translate(x, *ACCENTS)


def phone_key(word: Column, digraphs: bool = True) -> Column:
    """Words that sound alike by the rules have one key."""
    x = fold(F.lower(word))
    for a, b in DIGRAPHS if digraphs else ():
        x = F.replace(x, F.lit(a), F.lit(b))
    x = F.translate(x, *MERGED)
    for c in SYMBOLS:
        x = F.regexp_replace(x, f"{c}+", c)
    return x


def phones(word: Column, digraphs: bool = True) -> Column:
    """The key's letters are the phone symbols."""
    return F.filter(F.split(phone_key(word, digraphs), ""), lambda c: c != "")


def vocabulary(df: DataFrame, col: str = "text") -> DataFrame:
    """Distinct lower-case words of letters; words meet by partial aggregation before the shuffle."""
    return df.select(F.explode(t.words(F.col(col))).alias("word")).distinct()


def lexicon(words: DataFrame) -> DataFrame:
    """(word, rank, phones, phone_key): rank 2 is the reading without the digraph rules, if it differs."""
    one = F.struct(F.lit(1).alias("rank"), phones(F.col("word")).alias("phones"), phone_key(F.col("word")).alias("phone_key"))
    two = F.struct(F.lit(2).alias("rank"), phones(F.col("word"), False).alias("phones"), phone_key(F.col("word"), False).alias("phone_key"))
    both = F.when(one["phone_key"] != two["phone_key"], F.array(one, two)).otherwise(F.array(one))
    return words.select("word", F.inline(both))


def first_entry(lex: DataFrame) -> DataFrame:
    return lex.groupBy("word").agg(F.min_by(F.struct("phones", "phone_key"), "rank").alias("e")).select("word", "e.phones", "e.phone_key")


def attach(words: DataFrame, lex: DataFrame) -> DataFrame:
    """Words with their first pronunciation; null where the lexicon has none."""
    return words.join(first_entry(lex), "word", "left")


def confusions(lex: DataFrame) -> DataFrame:
    """Each word's successor in the sorted group of its key, around the end; words alone in a group have none."""
    w = Window.partitionBy("phone_key")
    o = w.orderBy("word")
    one = first_entry(lex).select("word", "phone_key")
    return one.withColumn("next", F.coalesce(F.lead("word").over(o), F.min("word").over(w))).where("next <> word").select("word", "next")


def corrupt(sentences: DataFrame, pairs: DataFrame, rate: float = 0.16, kinds: tuple[str, ...] = ("confusion",), seed: int = 1) -> DataFrame:
    """Sentences (doc_id, idx, text) through a recognizer's noise: (doc_id, idx, ref, hyp).

    confusion: a word gives way to the next of its sound group; filler: 'uh' before it; repetition:
    twice; deletion: gone. Each kind draws by its own hash of (doc, idx, position, seed). Words that
    are not drawn get keys that match nothing and spread over the partitions of the join.
    """
    words = sentences.select("doc_id", "idx", F.col("text").alias("ref"), F.posexplode(F.split("text", t.SPACE)).alias("j", "w"))

    def drawn(kind: int) -> Column:
        return t.h(t.key(F.col("doc_id"), F.col("idx"), F.col("j"), str(seed + kind))) % 1000 < int(round(rate * 1000))

    out = words.withColumn("hyp", F.col("w"))
    if "confusion" in kinds:
        swap = drawn(0) & F.col("w").rlike(r"^\p{L}+$")
        out = out.withColumn("at", F.when(swap, F.lower("w")).otherwise(F.concat(F.lit("#"), F.pmod(F.xxhash64("doc_id", "idx", "j"), F.lit(1 << 20)).cast("string")))).join(pairs.withColumnRenamed("word", "at"), "at", "left").withColumn("hyp", F.coalesce("next", "w"))
    if "filler" in kinds:
        out = out.withColumn("hyp", F.when(drawn(1), F.concat(F.lit("uh "), "hyp")).otherwise(F.col("hyp")))
    if "repetition" in kinds:
        out = out.withColumn("hyp", F.when(drawn(2), F.concat("hyp", F.lit(" "), "hyp")).otherwise(F.col("hyp")))
    if "deletion" in kinds:
        out = out.withColumn("hyp", F.when(drawn(3), "").otherwise(F.col("hyp")))
    lists = out.groupBy("doc_id", "idx").agg(F.first("ref").alias("ref"), F.sort_array(F.collect_list(F.struct("j", "hyp"))).alias("hs"))
    return lists.select("doc_id", "idx", "ref", F.trim(F.regexp_replace(F.array_join(F.transform("hs", lambda x: x["hyp"]), " "), " +", " ")).alias("hyp"))


def restore_marks(words: Column, every: int = 12) -> Column:
    """Rule baseline for punctuation: a period before a capital after at least three words, or at ``every`` words.

    words: array without marks; returns the array of marks ('' or '.').
    """
    zero = F.struct(F.lit(0).alias("run"), F.array().cast("array<string>").alias("marks"))

    def step(s: Column, i: Column) -> Column:
        capital = F.get(words, i + 1).rlike(r"^\p{Lu}")
        stop = F.coalesce((i == F.size(words) - 1) | (capital & (s["run"] >= 2)), F.lit(False)) | (s["run"] >= every - 1)
        return F.struct(F.when(stop, 0).otherwise(s["run"] + 1).alias("run"), F.concat(s["marks"], F.array(F.when(stop, ".").otherwise(""))).alias("marks"))

    return F.aggregate(F.when(F.size(words) > 0, F.sequence(F.lit(0), F.size(words) - 1)).otherwise(F.array().cast("array<int>")), zero, step, lambda s: s["marks"])


def closeness(vectors: DataFrame) -> DataFrame:
    """(word, phone_key, v) to the mean cosine of words of one key, in hash order, less that of words of different keys.

    Neighbours in a sorted group stand for its pairs, so a group of any size gives pairs in proportion.
    """

    def cosine(a: str, b: str) -> Column:
        dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
        return dot(F.col(a), F.col(b)) / F.sqrt(dot(F.col(a), F.col(a)) * dot(F.col(b), F.col(b)) + 1e-12)

    same = Window.partitionBy("phone_key").orderBy("word")
    bucket = vectors.withColumn("bucket", t.h(F.col("word")) % 64)
    other = Window.partitionBy("bucket").orderBy(F.md5(F.col("word").cast("binary")))
    rows = bucket.withColumn("s", F.lead("v").over(same)).withColumn("o", F.lead("v").over(other)).withColumn("ok", F.lead("phone_key").over(other))
    return rows.agg(F.avg(F.when(F.col("s").isNotNull(), cosine("v", "s"))).alias("same"), F.avg(F.when(F.col("o").isNotNull() & (F.col("ok") != F.col("phone_key")), cosine("v", "o"))).alias("other")).withColumn("closeness", F.col("same") - F.col("other"))


def calibrated_rate(sentences: DataFrame, pairs: DataFrame, target: float = 0.16, kinds: tuple[str, ...] = ("confusion", "filler", "repetition", "deletion"), start: float = 0.1, rounds: int = 3) -> tuple[float, float]:
    """Word rate at which the character error rate comes near the target, and the rate measured there."""
    from ..operators.evaluation import cer

    rate, got = start, 0.0
    for _ in range(rounds):
        got = float(cer(corrupt(sentences, pairs, rate, kinds)).first().cer or 0.0)
        if not got or abs(got - target) < 0.01:
            break
        rate = min(1.0, rate * target / got)
    return rate, got
