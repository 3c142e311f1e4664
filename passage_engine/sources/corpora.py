"""Corpora on the given tables: what stands for written, second-language, lecture and interview text."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as t

#: Documents with at least so many terminators before white space stand for lectures.
LECTURE_SENTENCES = 100


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def split_of(number: Column) -> Column:
    """80/10/10 by the last digit."""
    return F.when(number % 10 < 8, "train").when(number % 10 == 8, "dev").otherwise("test")


def groups(documents: DataFrame) -> DataFrame:
    """Exact copies share a group, named by the smallest doc_id: (digest, group_id).

    The shuffle carries 16-byte digests and ids, never texts.
    """
    return documents.groupBy(F.md5(F.col("text").cast("binary")).alias("digest")).agg(F.min("doc_id").alias("group_id"))


def with_split(documents: DataFrame) -> DataFrame:
    """Documents with group_id and split; copies stay on one side."""
    ids = documents.select("doc_id", F.md5(F.col("text").cast("binary")).alias("digest"))
    of = ids.join(groups(documents), "digest").select("doc_id", "group_id", split_of(F.col("group_id")).alias("split"))
    return documents.join(of, "doc_id")


def written(spark: SparkSession, sf_dir: str, second: bool = False) -> DataFrame:
    """English documents, or those in the other languages; newline paragraphs."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    docs = docs.where("lang <> 'en'" if second else "lang = 'en'")
    return t.with_sentences(docs).select("doc_id", F.lit("F-XX" if second else "F-EN").alias("corpus"), "lang", "n_sent", "sents")


def lectures(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    long = docs.where(F.size(F.regexp_extract_all("text", F.lit(r"([.!?]+)[ \t\r\f\n]"), F.lit(1))) >= LECTURE_SENTENCES)
    return t.with_sentences(long).select("doc_id", F.lit("F-LEC").alias("corpus"), "lang", "n_sent", "sents")


def interviews(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A document is one turn; doc_id = conv_id * 1000 + turn."""
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), "text", F.lit("en").alias("lang"))
    return t.with_sentences(turns).select("doc_id", F.lit("F-INT").alias("corpus"), "lang", "n_sent", "sents")


def coarse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A document is one conversation, a segment one turn: the upper level of a two-level structure."""
    turns = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("doc_id"), "turn", "text")
    lists = turns.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("turn", "text"))).alias("turns"))
    paragraphs = F.transform("turns", lambda x: F.regexp_replace(x["text"], "\n", " "))
    return lists.select("doc_id", F.lit("F-COARSE").alias("corpus"), F.lit("en").alias("lang"), t.sentence_array(paragraphs).alias("sents")).withColumn("n_sent", F.size("sents")).select("doc_id", "corpus", "lang", "n_sent", "sents")


def web(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), t.html_paragraphs(F.col("html")).alias("ps"))
    return pages.select("doc_id", F.lit("F-WEB").alias("corpus"), F.lit("xx").alias("lang"), t.sentence_array(F.col("ps")).alias("sents")).withColumn("n_sent", F.size("sents")).where("n_sent > 0").select("doc_id", "corpus", "lang", "n_sent", "sents")


def all_corpora(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = written(spark, sf_dir)
    for part in (written(spark, sf_dir, True), lectures(spark, sf_dir), interviews(spark, sf_dir), coarse(spark, sf_dir), web(spark, sf_dir)):
        out = out.unionByName(part)
    return out


def take_n(df: DataFrame, n: int, seed: int = 0, key: str = "doc_id") -> DataFrame:
    """A random sample of n rows that any engine can repeat: the n smallest md5 of id and seed."""
    return df.orderBy(F.md5(t.key(F.col(key), str(seed)).cast("binary")), key).limit(n)


def from_text(df: DataFrame, mode: str = "blank_line", text: str = "text") -> DataFrame:
    """Corpus creation from plain text: references at blank lines, or at every line end."""
    return t.with_sentences(df, text, mode)


def from_hierarchy(df: DataFrame, level: int) -> DataFrame:
    """(doc_id, path array of section numbers, text), one row a paragraph in order ``pos``, to labels of one level.

    A sentence closes a segment where the path cut to ``level`` numbers changes.
    """
    lists = df.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("pos", F.slice("path", 1, level).alias("cut"), "text"))).alias("ps"))
    sents = F.flatten(F.transform("ps", lambda p, i: F.transform(t.split_sentences(p["text"]), lambda s, j: F.struct(s.alias("text"), ((j == F.size(t.split_sentences(p["text"])) - 1) & ~F.coalesce(F.get(F.col("ps"), i + 1)["cut"] == p["cut"], F.lit(False))).alias("ends_para")))))
    return lists.select("doc_id", F.transform(sents, lambda s, i: F.struct(i.cast("int").alias("idx"), s["text"].alias("text"), t.count_words(s["text"]).alias("n_tok"), s["ends_para"].alias("ends_para"))).alias("sents")).withColumn("n_sent", F.size("sents"))
