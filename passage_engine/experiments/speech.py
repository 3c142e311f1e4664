"""Workloads on pronunciations, noise and pre-training objectives."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import register
from ..functions import phones as ph
from ..functions import pretrain
from ..functions import text as t
from ..operators import evaluation
from ..sources import corpora
from ..sources.corpora import table
from . import sql
from .sql import sentences, with_


def key_sql(x: str, digraphs: bool = True) -> str:
    x = f"translate(lower({x}), '{ph.ACCENTS[0]}', '{ph.ACCENTS[1]}')"
    for a, b in ph.DIGRAPHS if digraphs else ():
        x = f"replace({x}, '{a}', '{b}')"
    x = f"translate({x}, '{ph.MERGED[0]}', '{ph.MERGED[1]}')"
    for c in ph.SYMBOLS:
        x = f"regexp_replace({x}, '{c}+', '{c}', 'g')"
    return x


VOCAB = "vocab AS (SELECT DISTINCT word FROM (SELECT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM documents))"
KEYED = f"keyed AS (SELECT word, {key_sql('word')} AS k FROM vocab)"


def document_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ph.lexicon(ph.vocabulary(table(spark, sf_dir, "documents")))


@register("lexicon_first", with_(VOCAB, KEYED) + " SELECT word, k AS phone_key, length(k)::INT AS n FROM keyed")
def lexicon_first(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first pronunciation of every word."""
    return ph.first_entry(document_lexicon(spark, sf_dir)).select("word", "phone_key", F.size("phones").alias("n"))


@register("homophones", with_(VOCAB, KEYED) + " SELECT k AS phone_key, count(*)::BIGINT AS words, min(word) AS first_word FROM keyed GROUP BY k HAVING count(*) > 1")
def homophones(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = ph.first_entry(document_lexicon(spark, sf_dir))
    return words.groupBy("phone_key").agg(F.count("*").alias("words"), F.min("word").alias("first_word")).where("words > 1")


OOV_SQL = with_(VOCAB) + ", spoken AS (SELECT DISTINCT word FROM (SELECT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM conversations)) SELECT count(*)::BIGINT AS words, sum((word NOT IN (SELECT word FROM vocab))::INT)::BIGINT AS unknown FROM spoken"


@register("lexicon_oov", OOV_SQL)
def lexicon_oov(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of conversations without a pronunciation in the documents' lexicon."""
    got = ph.attach(ph.vocabulary(table(spark, sf_dir, "conversations")), document_lexicon(spark, sf_dir))
    return got.agg(F.count("*").alias("words"), F.sum(F.col("phone_key").isNull().cast("long")).alias("unknown"))


FOLD = f"regexp_replace(translate(lower({{0}}), '{ph.ACCENTS[0]}', '{ph.ACCENTS[1]}'), '[^ -~]', '?', 'g')"
NOISE = f"""nx AS (SELECT word, coalesce(lead(word) OVER (PARTITION BY k ORDER BY word), min(word) OVER (PARTITION BY k)) AS next FROM keyed),
tok AS (SELECT doc_id, idx, text, generate_subscripts(w, 1) - 1 AS j, unnest(w) AS w FROM (SELECT doc_id, idx, text, string_split_regex(text, '[ \\t\\r\\f]+') AS w FROM sents)),
sw AS (SELECT tok.*, CASE WHEN {sql.h("doc_id || '-' || idx || '-' || j || '-1'")} % 1000 < 160 AND regexp_full_match(w, '\\p{{L}}+') THEN lower(w) END AS at FROM tok),
hy AS (SELECT doc_id, idx, any_value(text) AS ref, string_agg(coalesce(next, w), ' ' ORDER BY j) AS hyp FROM sw LEFT JOIN nx ON nx.word = sw.at AND nx.next <> nx.word GROUP BY doc_id, idx)"""
VOCAB_INT = "vocab AS (SELECT DISTINCT word FROM (SELECT unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS word FROM conversations))"


def noisy_interviews(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    rows = t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", "text")
    return ph.corrupt(rows, ph.confusions(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations")))), **options)


@register("noise_words", with_(sentences("F-INT"), VOCAB_INT, KEYED, NOISE) + " SELECT doc_id, idx, hyp FROM hy WHERE hyp <> ref")
def noise_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sentences that the confusions changed."""
    return noisy_interviews(spark, sf_dir).where("hyp <> ref").select("doc_id", "idx", "hyp")


@register("noise_cer", with_(sentences("F-INT"), VOCAB_INT, KEYED, NOISE) + f", x AS (SELECT {FOLD.format('ref')} AS a, {FOLD.format('hyp')} AS b FROM hy) SELECT sum(levenshtein(a, b))::BIGINT AS edits, sum(length(a))::BIGINT AS chars, round(sum(levenshtein(a, b)) / sum(length(a)), 6) AS cer FROM x")
def noise_cer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Character error rate of the noisy interviews, on letters without accents."""
    n = noisy_interviews(spark, sf_dir)
    return evaluation.cer(n.select(*(F.regexp_replace(ph.fold(F.lower(c)), "[^ -~]", "?").alias(c) for c in ("ref", "hyp"))))


def _kinds_sql() -> str:
    """Edits of fillers, repetitions and deletions are insertions or losses of whole words."""
    hit = lambda k: f"{sql.h(f"doc_id || '-' || idx || '-' || j || '-{k}'")} % 1000 < 160"
    kinds = (("filler", 2, "'uh ' || w"), ("repetition", 3, "w || ' ' || w"), ("deletion", 4, "''"))
    rows = " UNION ALL ".join(f"SELECT '{n}' AS kind, doc_id, idx, any_value(text) AS ref, trim(regexp_replace(string_agg(CASE WHEN {hit(k)} THEN {x} ELSE w END, ' ' ORDER BY j), ' +', ' ', 'g')) AS hyp FROM tok GROUP BY doc_id, idx" for n, k, x in kinds)
    return with_(sentences("F-INT"), VOCAB_INT, KEYED, NOISE) + f""", kinds AS (SELECT 'confusion' AS kind, doc_id, idx, ref, hyp FROM hy UNION ALL {rows}), x AS (SELECT kind, {FOLD.format('ref')} AS a, {FOLD.format('hyp')} AS b FROM kinds)
SELECT kind, sum(levenshtein(a, b))::BIGINT AS edits, sum(length(a))::BIGINT AS chars, round(sum(levenshtein(a, b)) / sum(length(a)), 6) AS cer FROM x GROUP BY kind"""


@register("noise_kinds", _kinds_sql())
def noise_kinds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Character error rate of each kind of noise by itself, on letters without accents."""
    plain = lambda c: F.regexp_replace(ph.fold(F.lower(c)), "[^ -~]", "?").alias(c)
    parts = [evaluation.cer(noisy_interviews(spark, sf_dir, kinds=(k,)).select(plain("ref"), plain("hyp"))).withColumn("kind", F.lit(k)) for k in ("confusion", "filler", "repetition", "deletion")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


MARKS_SQL = with_(sentences("F-INT")) + ", e AS (SELECT count(*) FILTER (regexp_full_match(text, '.*[.!?]+'))::BIGINT AS n FROM sents) SELECT n AS sentences FROM e"


@register("marks_present", MARKS_SQL)
def marks_present(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sentences that close with a mark: the references of punctuation restoring."""
    return t.exploded(corpora.interviews(spark, sf_dir)).agg(F.sum(F.col("text").rlike(r"[.!?]+$").cast("long")).alias("sentences"))


@register("punct_rules")
def punct_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rule baseline's periods against the real ones, by precision, recall and F1 over word positions."""
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), F.split(F.regexp_replace("text", "\n", " "), " +").alias("w"))
    bare = turns.withColumn("bare", F.transform("w", lambda x: F.regexp_replace(x, "[.!?,]+$", "")))
    got = bare.select(F.transform(ph.restore_marks(F.col("bare")), lambda m: m != "").alias("pred"), F.transform("w", lambda x: x.rlike("[.!?]+$")).alias("ref"))
    return evaluation.document_prf(got, "pred", "ref")


#: A drawn sentence of each of at most 4,096 drawn documents, numbered densely from 0.
OTHERS = f"""drawn AS (SELECT doc_id, md5(doc_id || '-other') AS o, text FROM sents WHERE idx = {sql.h("doc_id || '-sentence'")} % n_sent),
others AS (SELECT (row_number() OVER (ORDER BY o, doc_id) - 1) AS slot, doc_id AS od, text AS other FROM (SELECT * FROM drawn ORDER BY o, doc_id LIMIT 4096)),
many AS (SELECT count(*) AS m FROM others),
s AS (SELECT doc_id, idx, text, lead(text) OVER (PARTITION BY doc_id ORDER BY idx) AS nxt FROM sents),
placed AS (SELECT s.*, {sql.h("doc_id || '-' || idx || '-slot'")} % m AS at, m FROM s, many WHERE nxt IS NOT NULL),
paired AS (SELECT p.doc_id, p.idx, p.text, p.nxt, CASE WHEN a.od = p.doc_id THEN b.other ELSE a.other END AS other,
  CASE WHEN a.od = p.doc_id THEN b.od ELSE a.od END AS od FROM placed p JOIN others a ON a.slot = p.at JOIN others b ON b.slot = (p.at + 1) % p.m)"""
NEXT_SQL = with_(sentences("F-INT"), OTHERS) + f""" SELECT doc_id::BIGINT AS doc_id, idx::INT AS i, text AS s1, CASE WHEN {sql.h("doc_id || '-' || idx || '-next'")} % 2 = 0 THEN nxt ELSE other END AS s2, ({sql.h("doc_id || '-' || idx || '-next'")} % 2 = 0)::INT AS y FROM paired"""


@register("pretrain_next", NEXT_SQL)
def pretrain_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of the objective, text by text: the next sentence, or a sentence of another document."""
    return pretrain.next_pairs(corpora.interviews(spark, sf_dir))


ORDER_SQL = with_(sentences("F-INT"), OTHERS) + f""", y AS (SELECT *, {sql.h("doc_id || '-' || idx || '-order'")} % 3 AS y FROM paired)
SELECT doc_id::BIGINT AS doc_id, idx::INT AS i, CASE WHEN y = 1 THEN nxt ELSE text END AS s1, CASE y WHEN 1 THEN text WHEN 2 THEN other ELSE nxt END AS s2, y::INT AS y FROM y"""


@register("pretrain_order", ORDER_SQL)
def pretrain_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of the three-way objective, text by text."""
    return pretrain.order_triples(corpora.interviews(spark, sf_dir))


@register("pretrain_span", with_(sentences("F-INT")) + f", s AS (SELECT DISTINCT doc_id, n_sent AS n FROM sents), p AS (SELECT doc_id, i, i + g AS j FROM (SELECT doc_id, n, unnest(range(n)) AS i FROM s), (VALUES (2), (3)) v(g) WHERE i + g < n) SELECT ({sql.h('doc_id || chr(45) || i || chr(45) || j || chr(45) || chr(115)')} % 2)::INT AS y, count(*)::BIGINT AS pairs FROM p GROUP BY 1")
def pretrain_span(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pretrain.span_order(corpora.interviews(spark, sf_dir), 3).groupBy("y").agg(F.count("*").alias("pairs"))


WORDS_SQL = with_(sentences("F-INT")) + f""", j AS (SELECT doc_id, idx, n_tok, unnest(range(n_tok)) AS j FROM sents),
k AS (SELECT 'shuffled' AS objective, ({sql.h("doc_id || '-' || idx || '-' || (j // 3) || '-shuffle'")} % 1000 < 150 AND (j // 3) * 3 + 3 <= n_tok)::INT AS y FROM j
UNION ALL SELECT 'masked', ({sql.h("doc_id || '-' || idx || '-' || j || '-mask'")} % 1000 < 150)::INT FROM j)
SELECT objective, (SELECT count(*) FROM sents)::BIGINT AS rows, sum(y)::BIGINT AS targets FROM k GROUP BY objective"""


@register("pretrain_words", WORDS_SQL)
def pretrain_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of two token-level objectives: shuffled spans and masked tokens."""
    docs = corpora.interviews(spark, sf_dir)
    return _objectives({"shuffled": pretrain.word_order(docs, 3), "masked": pretrain.mask_tokens(docs, 0.15)})


@register("pretrain_replaced")
def pretrain_replaced(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the replaced-token objective: words of the frequency sampler in place of drawn ones."""
    docs = corpora.interviews(spark, sf_dir)
    return _objectives({"replaced": pretrain.replace_tokens(docs, pretrain.counted_words(docs), 0.15)})


def _objectives(parts: dict[str, DataFrame]) -> DataFrame:
    out = None
    for name, p in parts.items():
        x = p.agg(F.count("*").alias("rows"), F.sum(F.size(F.filter("y", lambda v: v != 0))).cast("long").alias("targets")).withColumn("objective", F.lit(name))
        out = x if out is None else out.unionByName(x)
    return out
