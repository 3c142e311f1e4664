"""Queries on sources, sinks, tokens and the public SQL functions."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import register
from ..functions import registry, tokens
from ..operators import evaluation
from ..plans.windows import Adaptive, Fixed
from ..session import shared_base
from ..sources import corpora, io
from ..sources.corpora import table
from .core import scored, with_windows
from .learned import VOCAB
from .speech import key_sql
from .sql import CUE, sentences, with_


@register("scan_json_corrupt", "SELECT count(*)::BIGINT AS rows, 1::BIGINT AS malformed FROM nation")
def scan_json_corrupt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """JSON lines with one malformed line."""
    path = f"{shared_base(spark)}/json-{uuid.uuid4().hex}"
    lines = table(spark, sf_dir, "nation").select(F.to_json(F.struct("n_nationkey", "n_name")).alias("value"))
    lines.unionByName(spark.createDataFrame([("{broken",)], "value string")).write.text(path)
    back = io.read_json(spark, path, "n_nationkey int, n_name string").select("n_nationkey", "_corrupt").cache()
    out = back.agg(F.sum(F.col("_corrupt").isNull().cast("long")).alias("rows"), F.sum(F.col("_corrupt").isNotNull().cast("long")).alias("malformed"))
    return out


@register("sink_roundtrip", "SELECT lang, count(*)::BIGINT AS docs, sum(n_chars)::BIGINT AS chars FROM documents WHERE lang <> 'en' GROUP BY lang")
def sink_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parquet partitioned by language; the filter prunes folders."""
    path = f"{shared_base(spark)}/sink-{uuid.uuid4().hex}"
    io.write_partitioned(table(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars"), path, "lang")
    return spark.read.parquet(path).where("lang <> 'en'").groupBy("lang").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))


@register("resume_todo", "SELECT doc_id FROM documents WHERE doc_id % 3 <> 0")
def resume_todo(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents").select("doc_id")
    return io.unfinished(d, d.where("doc_id % 3 = 0"))


@register("source_transcript", "SELECT conv_id AS key, turn::INT AS turn, text FROM conversations WHERE text IS NOT NULL")
def source_transcript(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The conversations as transcript lines, read by the rule of the Python data source for transcripts."""
    lines = table(spark, sf_dir, "conversations").select(F.concat("conv_id", F.lit("|"), "turn", F.lit("|"), "text").alias("line"))
    return io.read_transcript(lines)


@register("udf_scalar", with_(sentences("F-INT")) + " SELECT doc_id, count(*)::INT AS n FROM sents GROUP BY doc_id")
def udf_scalar(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Probabilities of each turn by the registered function: one for each sentence."""
    registry.register(spark)
    table(spark, sf_dir, "conversations").createOrReplaceTempView("pe_turns")
    return spark.sql("SELECT conv_id * 1000 + turn AS doc_id, size(boundary_probs(text)) AS n FROM pe_turns")


@register("udf_agg", "SELECT round(2.0 * count(*) FILTER (quality = 1 AND doc_id % 2 = 0) / (count(*) FILTER (quality = 1) + count(*) FILTER (doc_id % 2 = 0)), 6) AS f1 FROM labels")
def udf_agg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grouped aggregate F1."""
    registry.register(spark)
    table(spark, sf_dir, "labels").createOrReplaceTempView("pe_labels")
    return spark.sql("SELECT round(boundary_f1(doc_id % 2 = 0, quality = 1), 6) AS f1 FROM pe_labels")


@register("udtf_segments", with_(sentences("F-INT")) + f", x AS (SELECT doc_id, idx, sum((({CUE}))::INT) OVER (PARTITION BY doc_id ORDER BY idx ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS k FROM sents) SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY min(idx))::INT - 1 AS seg_no, min(idx)::INT AS first, max(idx)::INT AS last FROM x GROUP BY doc_id, coalesce(k, 0)")
def udtf_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table function, called laterally."""
    registry.register(spark)
    table(spark, sf_dir, "conversations").createOrReplaceTempView("pe_turns")
    return spark.sql("SELECT conv_id * 1000 + turn AS doc_id, s.seg_no, s.first, s.last FROM pe_turns, LATERAL segments_of(text) s")


PHONES_SQL = "WITH w AS (SELECT DISTINCT word FROM (SELECT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM conversations)), x AS (SELECT word, " + key_sql("word") + " AS k FROM w) SELECT word, k, length(k)::INT AS n FROM x"


@register("sql_phones", PHONES_SQL)
def sql_phones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The registered functions on every word of the conversations."""
    registry.register(spark)
    words = table(spark, sf_dir, "conversations").selectExpr(r"explode(regexp_extract_all(lower(text), r'(\p{L}+)', 1)) AS word").distinct()
    return spark.sql("SELECT word, phone_key(word) AS k, size(phones(word)) AS n FROM {words}", words=words)


@register("subword_counts")
def subword_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pieces of the interviews by a public vocabulary."""
    docs = corpora.interviews(spark, sf_dir)
    return tokens.count_pieces(tokens.encode(docs, tokens.load_vocab(VOCAB))).agg(F.count("*").alias("docs"), F.sum("n").alias("pieces"), F.sum("sents").alias("sents"))


@register("work_pieces")
def work_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows and work when the limit counts pieces, not words: both schedules on the interviews."""
    docs = scored(tokens.as_pieces(corpora.interviews(spark, sf_dir), tokens.load_vocab(VOCAB)))
    rows = [evaluation.work(with_windows(docs, p)).withColumn("policy", F.lit(n)) for n, p in (("fixed 5", Fixed(5)), ("adaptive 10", Adaptive(10)))]
    return rows[0].unionByName(rows[1])
