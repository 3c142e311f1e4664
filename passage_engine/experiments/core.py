"""Workloads on windows, statistics, accuracy of deterministic scorers, annotation and readability."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import register
from ..functions import text as t
from ..models import lexical
from ..operators import annotate, evaluation
from ..plans import windows as win
from ..plans.windows import Adaptive, Fixed
from ..sources import corpora
from ..sources.corpora import table
from . import sql
from .sql import CUE, document_lists, sentences, window_walk, with_

STEPS = (1, 2, 5, 10, 15, 20)


def scored(corpus: DataFrame) -> DataFrame:
    """Arrays that window plans take: n_tok and the context-free cue's decisions."""
    return corpus.withColumn("toks", F.transform("sents", lambda s: s["n_tok"])).withColumn("positive", F.transform("sents", lexical.cue_positive))


def with_windows(corpus: DataFrame, policy) -> DataFrame:
    return corpus.withColumn("wins", win.window_array(F.col("toks"), F.col("positive"), policy))


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def work_rows(corpus: DataFrame, policies: list) -> DataFrame:
    """Work of several schedules over one corpus; the policies' windows come from one scan."""
    cols = [F.struct(F.lit("fixed" if isinstance(p, Fixed) else "adaptive").alias("policy"), F.lit(p.step if isinstance(p, Fixed) else p.lookback).alias("lookback"), win.window_array(F.col("toks"), F.col("positive"), p).alias("wins")) for p in policies]
    rows = corpus.select("doc_id", "n_sent", F.inline(F.array(*cols)))
    return evaluation.work(rows, "policy", "lookback")


HEADLINE_SQL = with_(sentences("F-EN"), document_lists(), window_walk("VALUES ('fixed', 5), ('adaptive', 10)")) + """
SELECT policy, b AS lookback, count(DISTINCT doc_id)::BIGINT AS docs, count(*)::BIGINT AS passes, sum(last - first + 1)::BIGINT AS sents_encoded, (sum(last - first + 1) - (SELECT count(*) FROM sents))::BIGINT AS sents_repeated FROM walk GROUP BY policy, b
UNION ALL SELECT 'local', 1, count(DISTINCT doc_id)::BIGINT, count(*)::BIGINT, count(*)::BIGINT, 0::BIGINT FROM sents
"""


@register("headline_work", HEADLINE_SQL)
def headline_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed step 5 and adaptive look-back 10 against one pass for each break."""
    en = scored(corpora.written(spark, sf_dir)).where("n_sent > 0")
    local = en.agg(F.count("*").alias("docs"), F.sum(F.col("n_sent").cast("long")).alias("passes")).select(F.lit("local").alias("policy"), F.lit(1).alias("lookback"), "docs", "passes", F.col("passes").alias("sents_encoded"), F.lit(0).cast("long").alias("sents_repeated"))
    return work_rows(en, [Fixed(5), Adaptive(10)]).unionByName(local)


def _sweep_sql(policy: str) -> str:
    values = "VALUES " + ", ".join(f"('{policy}', {b})" for b in STEPS)
    return with_(sentences("F-EN"), document_lists(), window_walk(values)) + """
SELECT policy, b AS lookback, count(DISTINCT doc_id)::BIGINT AS docs, count(*)::BIGINT AS passes, sum(last - first + 1)::BIGINT AS sents_encoded, (sum(last - first + 1) - (SELECT count(*) FROM sents))::BIGINT AS sents_repeated FROM walk GROUP BY policy, b"""


@register("sweep_fixed_work", _sweep_sql("fixed"))
def sweep_fixed_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    return work_rows(scored(corpora.written(spark, sf_dir)).where("n_sent > 0"), [Fixed(b) for b in STEPS])


@register("sweep_adaptive_work", _sweep_sql("adaptive"))
def sweep_adaptive_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    return work_rows(scored(corpora.written(spark, sf_dir)).where("n_sent > 0"), [Adaptive(b) for b in STEPS])


@register("windows_adaptive", with_(sentences("F-EN", "F-XX"), document_lists(), window_walk("VALUES ('adaptive', 10)")) + " SELECT corpus, doc_id, (row_number() OVER (PARTITION BY corpus, doc_id ORDER BY first))::INT AS win_no, first::INT AS first, last::INT AS last FROM walk")
def windows_adaptive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every window of the adaptive schedule, one row each."""
    docs = scored(corpora.written(spark, sf_dir).unionByName(corpora.written(spark, sf_dir, True)))
    # the fold stands in the generator: of a column, Spark would infer a filter and fold every document again in it
    rows = docs.select("corpus", "doc_id", F.posexplode(win.window_array(F.col("toks"), F.col("positive"), Adaptive(10))).alias("k", "w"))
    return rows.select("corpus", "doc_id", (F.col("k") + 1).alias("win_no"), "w.first", "w.last")


ALL = ("F-EN", "F-XX", "F-LEC", "F-INT", "F-COARSE")
STATS = """, {by} count(DISTINCT doc_id)::BIGINT AS docs, round(count(*) / count(DISTINCT doc_id), 4) AS s_per_doc, round(sum(n_tok) / count(*), 4) AS slen,
round(sum(ends_para::INT) / count(DISTINCT doc_id), 4) AS p_per_doc, round(count(*) / sum(ends_para::INT), 4) AS s_per_p"""


def text_corpora(spark: SparkSession, sf_dir: str) -> DataFrame:
    return union([corpora.written(spark, sf_dir), corpora.written(spark, sf_dir, True), corpora.lectures(spark, sf_dir), corpora.interviews(spark, sf_dir), corpora.coarse(spark, sf_dir)])


@register("corpus_stats", with_(sentences(*ALL)) + " SELECT corpus" + STATS.format(by="") + " FROM sents GROUP BY corpus")
def corpus_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return evaluation.describe(text_corpora(spark, sf_dir), "corpus")


@register("corpus_stats_web")
def corpus_stats_web(spark: SparkSession, sf_dir: str) -> DataFrame:
    return evaluation.describe(corpora.web(spark, sf_dir), "corpus")


GROUPS = "grp AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS g FROM documents), spl AS (SELECT doc_id, g AS group_id, CASE WHEN g % 10 < 8 THEN 'train' WHEN g % 10 = 8 THEN 'dev' ELSE 'test' END AS split FROM grp)"


@register("corpus_stats_by_split", with_(sentences("F-EN", "F-XX"), GROUPS) + " SELECT corpus, split" + STATS.format(by="") + " FROM sents JOIN spl USING (doc_id) GROUP BY corpus, split")
def corpus_stats_by_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = corpora.written(spark, sf_dir).unionByName(corpora.written(spark, sf_dir, True))
    split = corpora.with_split(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "split")
    return evaluation.describe(docs.join(split, "doc_id"), "corpus", "split")


@register("split_sizes", with_(GROUPS) + " SELECT split, count(*)::BIGINT AS docs, count(DISTINCT group_id)::BIGINT AS groups FROM spl GROUP BY split")
def split_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = corpora.with_split(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.groupBy("split").agg(F.count("*").alias("docs"), F.countDistinct("group_id").alias("groups"))


@register("split_leak", with_(GROUPS) + " SELECT count(*)::BIGINT AS texts, coalesce(sum((n > 1)::INT), 0)::BIGINT AS leaks FROM (SELECT group_id, count(DISTINCT split) AS n FROM spl GROUP BY group_id)")
def split_leak(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = corpora.with_split(table(spark, sf_dir, "documents").select("doc_id", "text"))
    n = d.groupBy("group_id").agg(F.countDistinct("split").alias("n"))
    return n.agg(F.count("*").alias("texts"), F.sum((F.col("n") > 1).cast("long")).alias("leaks"))


# -- accuracy of the scorers that SQL can repeat ---------------------------------------------------

PRF = """count(*) FILTER (p AND r)::BIGINT AS tp, count(*) FILTER (p AND NOT r)::BIGINT AS fp, count(*) FILTER (NOT p AND r)::BIGINT AS fn"""
PRF_OUT = """tp, fp, fn, round(CASE WHEN tp + fp > 0 THEN tp / (tp + fp) ELSE 0 END, 6) AS p, round(CASE WHEN tp + fn > 0 THEN tp / (tp + fn) ELSE 0 END, 6) AS r, round(CASE WHEN 2 * tp + fp + fn > 0 THEN 2 * tp / (2 * tp + fp + fn) ELSE 0 END, 6) AS f1"""


def _acc_sql(*names: str, pred: str = CUE) -> str:
    return with_(sentences(*names)) + f" SELECT corpus, {PRF_OUT} FROM (SELECT corpus, {PRF} FROM (SELECT corpus, {pred} AS p, ends_para AS r FROM sents WHERE idx < n_sent - 1) GROUP BY corpus)"


def acc_cue(corpus: DataFrame) -> DataFrame:
    return evaluation.document_prf(corpus.withColumn("positive", F.transform("sents", lexical.cue_positive)).withColumn("ref", F.transform("sents", lambda s: s["ends_para"])), "positive", "ref", "corpus")


@register("agg_prf", _acc_sql(*ALL))
def agg_prf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return acc_cue(text_corpora(spark, sf_dir))


@register("acc_written_cue", _acc_sql("F-EN", "F-COARSE"))
def acc_written_cue(spark: SparkSession, sf_dir: str) -> DataFrame:
    return acc_cue(corpora.written(spark, sf_dir).unionByName(corpora.coarse(spark, sf_dir)))


@register("acc_second_lang", _acc_sql("F-XX"))
def acc_second_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return acc_cue(corpora.written(spark, sf_dir, True))


@register("acc_lecture", _acc_sql("F-LEC"))
def acc_lecture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return acc_cue(corpora.lectures(spark, sf_dir))


@register("acc_interview", _acc_sql("F-INT"))
def acc_interview(spark: SparkSession, sf_dir: str) -> DataFrame:
    return acc_cue(corpora.interviews(spark, sf_dir))


DISSIMILAR = """ws AS (SELECT corpus, doc_id, idx, n_sent, ends_para, list_distinct(regexp_extract_all(lower(text), '\\p{L}+')) AS w FROM sents),
side AS (SELECT corpus, doc_id, idx, n_sent, ends_para,
  list_distinct(flatten(list(w) OVER (PARTITION BY corpus, doc_id ORDER BY idx ROWS BETWEEN 2 PRECEDING AND CURRENT ROW))) AS l,
  list_distinct(coalesce(flatten(list(w) OVER (PARTITION BY corpus, doc_id ORDER BY idx ROWS BETWEEN 1 FOLLOWING AND 3 FOLLOWING)), []::VARCHAR[])) AS r FROM ws),
d AS (SELECT *, CASE WHEN len(list_distinct(list_concat(l, r))) = 0 THEN 1.0 ELSE round(1 - len(list_intersect(l, r)) / len(list_distinct(list_concat(l, r))), 6) END AS d FROM side)"""
COHESION_SQL = with_(sentences("F-EN", "F-INT"), DISSIMILAR) + """
SELECT corpus, count(*)::BIGINT AS breaks, round(avg(d), 4) AS mean, sum((d >= 0.95)::INT)::BIGINT AS dissimilar FROM d WHERE idx < n_sent - 1 GROUP BY corpus"""


@register("cohesion_scores", COHESION_SQL)
def cohesion_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lexical dissimilarity of the three sentences on either side of each break."""
    docs = corpora.written(spark, sf_dir).unionByName(corpora.interviews(spark, sf_dir))
    rows = docs.select("corpus", "n_sent", F.posexplode(lexical.cohesion(F.col("sents"), 3)).alias("idx", "d")).where("idx < n_sent - 1")
    return rows.groupBy("corpus").agg(F.count("*").alias("breaks"), F.round(F.avg("d"), 4).alias("mean"), F.sum((F.col("d") >= 0.95).cast("long")).alias("dissimilar"))


BEYOND_SQL = with_(sentences("F-EN", "F-COARSE"), DISSIMILAR) + f""", m AS (SELECT corpus, idx, n_sent, ends_para AS r,
  d > avg(d) OVER (PARTITION BY corpus, doc_id) + 0.5 * sqrt(avg(d * d) OVER (PARTITION BY corpus, doc_id) - (avg(d) OVER (PARTITION BY corpus, doc_id)) ** 2 + 1e-12) AS p FROM d)
SELECT corpus, {PRF_OUT} FROM (SELECT corpus, {PRF} FROM m WHERE idx < n_sent - 1 GROUP BY corpus)"""


@register("acc_written_cohesion", BEYOND_SQL)
def acc_written_cohesion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Unsupervised baseline: dissimilarity beyond mean + c * deviation of the document."""
    docs = corpora.written(spark, sf_dir).unionByName(corpora.coarse(spark, sf_dir))
    return evaluation.document_prf(docs.withColumn("positive", lexical.cohesion_positive(F.col("sents"))).withColumn("ref", F.transform("sents", lambda s: s["ends_para"])), "positive", "ref", "corpus")


TRIVIAL_SQL = with_(sentences("F-EN")) + f""", m AS (SELECT 'none' AS model, doc_id, idx, n_sent, ends_para AS r, false AS p FROM sents UNION ALL SELECT 'all', doc_id, idx, n_sent, ends_para, true FROM sents
UNION ALL SELECT 'every4', doc_id, idx, n_sent, ends_para, idx % 4 = 3 FROM sents UNION ALL SELECT 'random', doc_id, idx, n_sent, ends_para, {sql.h("doc_id || '-' || idx || '-random'")} % 100 < 25 FROM sents)
SELECT model, {PRF_OUT} FROM (SELECT model, {PRF} FROM m WHERE idx < n_sent - 1 GROUP BY model)"""


@register("acc_trivial", TRIVIAL_SQL)
def acc_trivial(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baselines without a model: none, all, every fourth, at random."""
    rows = t.exploded(corpora.written(spark, sf_dir))
    preds = {"none": F.lit(False), "all": F.lit(True), "every4": F.col("idx") % 4 == 3, "random": t.h(t.key(F.col("doc_id"), F.col("idx"), "random")) % 100 < 25}
    rows = rows.select("idx", "n_sent", "ends_para", F.inline(F.array(*(F.struct(F.lit(m).alias("model"), p.alias("is_boundary")) for m, p in preds.items()))))
    return evaluation.prf(rows, "model")


# -- training samples ------------------------------------------------------------------------------

FORWARD_SQL = with_(sentences("F-EN")) + """, d AS (SELECT doc_id, any_value(n_sent) AS n FROM sents GROUP BY doc_id),
w AS (SELECT doc_id, s AS first, least(s + 60, n) - 1 AS last FROM (SELECT doc_id, n, unnest(range(0, n, {step})) AS s FROM d))
SELECT count(*)::BIGINT AS samples, sum(last - first + 1)::BIGINT AS sents FROM w"""


@register("train_samples_fixed", FORWARD_SQL.format(step=10))
def train_samples_fixed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples by a fixed forward step of 10 and at most 60 sentences."""
    w = corpora.written(spark, sf_dir).select(F.inline(win.forward_windows(F.col("n_sent"))))
    return w.agg(F.count("*").alias("samples"), F.sum((F.col("last") - F.col("first") + 1).cast("long")).alias("sents"))


@register("train_samples_ref", with_(sentences("F-EN"), document_lists("ends_para"), window_walk("VALUES ('adaptive', 10)")) + " SELECT count(*)::BIGINT AS samples, sum(last - first + 1)::BIGINT AS sents FROM walk")
def train_samples_ref(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples by the adaptive schedule on references: fewer than by the fixed step."""
    docs = scored(corpora.written(spark, sf_dir)).withColumn("ref", F.transform("sents", lambda s: s["ends_para"]))
    w = docs.select(F.inline(win.reference_windows(F.col("toks"), F.col("ref"))))
    return w.agg(F.count("*").alias("samples"), F.sum((F.col("last") - F.col("first") + 1).cast("long")).alias("sents"))


OVERLONG_SQL = with_(sentences("F-EN", "F-XX")) + """, d AS (SELECT corpus, doc_id, any_value(n_sent) AS n, list(n_tok ORDER BY idx) AS t FROM sents GROUP BY corpus, doc_id),
w AS (SELECT corpus, doc_id, s AS first, t[s + 1:least(s + 60, n)] AS t FROM (SELECT corpus, doc_id, n, t, unnest(range(0, n, 10)) AS s FROM d)),
long AS (SELECT *, list_sum(t) AS total FROM w),
pre AS (SELECT *, list_count(list_filter(list_transform(range(1, len(t) + 1), lambda i: list_sum(t[1:i])), lambda q: q <= 511)) AS k FROM long WHERE total > 511),
cap AS (SELECT *, list_max(list_filter(range(1, 512), lambda m: list_sum(list_transform(t, lambda x: least(x, m))) <= 511)) AS m FROM pre)
SELECT 'whole' AS version, count(*)::BIGINT AS samples, coalesce(sum(len(t)), 0)::BIGINT AS sents, coalesce(sum(total), 0)::BIGINT AS tokens FROM long WHERE total <= 511
UNION ALL SELECT 'cut', count(*)::BIGINT, coalesce(sum(greatest(k, 1)), 0)::BIGINT, coalesce(sum(CASE WHEN k = 0 THEN least(t[1], 511) ELSE list_sum(t[1:k]) END), 0)::BIGINT FROM pre
UNION ALL SELECT 'trim', count(*)::BIGINT, coalesce(sum(len(t)), 0)::BIGINT, coalesce(sum(least(511, list_sum(list_transform(t, lambda x: least(x, m))) + least(511 - list_sum(list_transform(t, lambda x: least(x, m))), len(list_filter(t, lambda x: x > m))))), 0)::BIGINT FROM cap"""


def samples(docs: DataFrame) -> DataFrame:
    """Fixed-step samples; over-long ones in both versions (cut, trim), from one scan."""
    rows = docs.select("corpus", "doc_id", "toks", F.inline(win.forward_windows(F.col("n_sent"))))
    rows = rows.withColumn("t", F.slice("toks", F.col("first") + 1, F.col("last") - F.col("first") + 1))
    total = F.aggregate("t", F.lit(0), lambda a, x: a + x)
    both = F.array(F.struct(F.lit("cut").alias("version"), win.cut(F.col("t")).alias("toks")), F.struct(F.lit("trim").alias("version"), win.trim(F.col("t")).alias("toks")))
    whole = F.array(F.struct(F.lit("whole").alias("version"), F.col("t").alias("toks")))
    return rows.select("corpus", "doc_id", "first", F.inline(F.when(total > win.MAX_TOKENS, both).otherwise(whole)))


@register("overlong_pool", OVERLONG_SQL)
def overlong_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = scored(corpora.written(spark, sf_dir).unionByName(corpora.written(spark, sf_dir, True)))
    s = samples(docs)
    return s.groupBy("version").agg(F.count("*").alias("samples"), F.sum(F.size("toks").cast("long")).alias("sents"), F.sum(F.aggregate("toks", F.lit(0), lambda a, x: a + x).cast("long")).alias("tokens"))


@register("timing_sample", "SELECT doc_id FROM documents WHERE lang = 'en' ORDER BY md5(doc_id || '-0'), doc_id LIMIT 1000")
def timing_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.take_n(table(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id"), 1000)


@register("reading_sample", with_(sentences("F-LEC")) + ", d AS (SELECT DISTINCT doc_id FROM sents) SELECT doc_id FROM d ORDER BY md5(doc_id || '-0'), doc_id LIMIT 8")
def reading_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.take_n(corpora.lectures(spark, sf_dir).select("doc_id"), 8)


RENDER_SQL = with_(sentences("F-LEC")) + f""", d AS (SELECT DISTINCT doc_id FROM sents), s AS (SELECT doc_id FROM d ORDER BY md5(doc_id || '-0'), doc_id LIMIT 8),
x AS (SELECT doc_id, string_agg(text || CASE WHEN {CUE} THEN chr(10) ELSE ' ' END, '' ORDER BY idx) AS y FROM sents JOIN s USING (doc_id) GROUP BY doc_id)
SELECT doc_id, regexp_replace(y, '[ \\n]+$', '') AS shown FROM x"""


@register("render_segments", RENDER_SQL)
def render_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = scored(corpora.take_n(corpora.lectures(spark, sf_dir), 8))
    return docs.select("doc_id", t.render(F.col("sents"), F.col("positive")).alias("shown"))


# -- annotation ------------------------------------------------------------------------------------

VOTES = f"""ann(annotator, rate) AS (VALUES (1, 5), (2, 10), (3, 15), (4, 25), (5, 40)),
votes AS (SELECT doc_id, idx, n_sent, ends_para, annotator, CASE WHEN ends_para <> ({sql.h("doc_id || '-' || idx || '-' || annotator")} % 100 < rate) THEN 1 ELSE 0 END AS vote FROM sents, ann)"""
LOO = f"""peers AS (SELECT *, 2 * (sum(vote) OVER (PARTITION BY doc_id, idx) - vote) > 4 AS peer FROM votes),
loo AS (SELECT doc_id, annotator, {PRF_OUT} FROM (SELECT doc_id, annotator, {PRF} FROM (SELECT doc_id, annotator, vote = 1 AS p, peer AS r FROM peers) GROUP BY doc_id, annotator)),
ranked AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY f1 DESC, annotator) AS rank FROM loo)"""


def interview_votes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.synthetic_votes(t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", "n_sent", "ends_para"))


@register("ann_screen", with_(sentences("F-EN"), VOTES) + f" SELECT * FROM (SELECT annotator, {PRF_OUT} FROM (SELECT annotator, {PRF} FROM (SELECT annotator, vote = 1 AS p, ends_para AS r FROM votes WHERE idx < n_sent - 1) GROUP BY annotator)) WHERE f1 * 100 > 60")
def ann_screen(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.screen(annotate.synthetic_votes(t.exploded(corpora.written(spark, sf_dir)).select("doc_id", "idx", "n_sent", "ends_para")))


@register("ann_loo", with_(sentences("F-INT"), VOTES, LOO) + " SELECT doc_id, annotator, tp, fp, fn, p, r, f1, rank::INT AS rank FROM ranked")
def ann_loo(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.leave_one_out(interview_votes(spark, sf_dir))


def _voted(spark, sf_dir, keep: int) -> DataFrame:
    votes = interview_votes(spark, sf_dir)
    refs = t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", "n_sent", "ends_para")
    got = annotate.vote(votes, keep, 3) if keep < 5 else annotate.majority(votes, 3)
    return evaluation.prf(got.join(refs, ["doc_id", "idx"]))


def _voted_sql(source: str) -> str:
    return f", d AS (SELECT doc_id, idx, any_value(n_sent) AS n_sent, any_value(ends_para) AS r, sum(vote) >= 3 AS p FROM {source} GROUP BY doc_id, idx) SELECT {PRF_OUT} FROM (SELECT {PRF} FROM d WHERE idx < n_sent - 1)"


@register("ann_vote4", with_(sentences("F-INT"), VOTES, LOO) + _voted_sql("(SELECT votes.* FROM votes JOIN ranked USING (doc_id, annotator) WHERE rank <= 4)"))
def ann_vote4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _voted(spark, sf_dir, 4)


@register("ann_vote5", with_(sentences("F-INT"), VOTES) + _voted_sql("votes"))
def ann_vote5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _voted(spark, sf_dir, 5)


@register("ann_agreement", with_(sentences("F-INT"), VOTES) + ", e AS (SELECT doc_id, idx, (min(vote) = max(vote))::INT AS same FROM votes GROUP BY doc_id, idx) SELECT count(*)::BIGINT AS sentences, sum(same)::BIGINT AS same, round(sum(same) / count(*), 6) AS share FROM e")
def ann_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.agreement(interview_votes(spark, sf_dir))


ASSIGN_SQL = with_(sentences("F-INT")) + f""", a AS (SELECT unnest(range(1, 13))::INT AS annotator), x AS (SELECT doc_id, idx, annotator, row_number() OVER (PARTITION BY doc_id, idx ORDER BY {sql.h("doc_id || '-' || idx || '-' || annotator")}, annotator) AS k FROM sents, a)
SELECT annotator, count(*)::BIGINT AS jobs FROM x WHERE k <= 5 GROUP BY annotator"""


@register("ann_assign", ASSIGN_SQL)
def ann_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five of twelve annotators for each sentence; the jobs of each annotator."""
    rows = t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx")
    pool = spark.range(1, 13).select(F.col("id").cast("int").alias("annotator"))
    return annotate.assign(rows, pool).groupBy("annotator").agg(F.count("*").alias("jobs"))


# -- readability -----------------------------------------------------------------------------------


def returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as returns: a job is a worker's minute-stamped answer, the model by the worker's parity."""
    e = table(spark, sf_dir, "events")
    return e.select(F.col("event_id").alias("job_id"), F.col("event_id").alias("doc_id"), F.when(F.col("user_id") % 2 == 0, "block").otherwise("local").alias("model"), F.col("user_id").alias("worker_id"), F.col("event_type").alias("question"), (F.get_json_object("props", "$.k").cast("long") % 2 == 0).cast("int").alias("correct"), F.col("value").alias("minutes"))


RETURNS = "ret AS (SELECT event_id AS job_id, CASE WHEN user_id % 2 = 0 THEN 'block' ELSE 'local' END AS model, user_id AS worker_id, event_type AS question, ((props::JSON->>'$.k')::BIGINT % 2 = 0)::INT AS correct, value AS minutes FROM events), eff AS (SELECT * FROM ret WHERE minutes BETWEEN 6 AND 20)"


@register("read_effective", with_(RETURNS) + " SELECT model, count(*)::BIGINT AS n, round(avg(minutes), 6) AS minutes FROM eff GROUP BY model")
def read_effective(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.effective(returns(spark, sf_dir)).groupBy("model").agg(F.count("*").alias("n"), F.round(F.avg("minutes"), 6).alias("minutes"))


@register("read_accuracy", with_(RETURNS) + " SELECT model, count(DISTINCT job_id)::BIGINT AS jobs, count(*)::BIGINT AS answers, round(avg(correct), 6) AS accuracy FROM eff GROUP BY model")
def read_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return annotate.answer_accuracy(returns(spark, sf_dir))


@register("read_plan", with_(sentences("F-LEC")) + f", d AS (SELECT DISTINCT doc_id FROM sents), s AS (SELECT doc_id FROM d ORDER BY md5(doc_id || '-0'), doc_id LIMIT 8), j AS (SELECT doc_id, model, copy, {sql.h('doc_id || chr(45) || model || chr(45) || copy')} AS job_id FROM s, (VALUES ('block'), ('local')) m(model), (SELECT unnest(range(50))::INT AS copy)) SELECT model, count(*)::BIGINT AS jobs, count(DISTINCT doc_id)::BIGINT AS docs, sum(job_id % 1000)::BIGINT AS mark FROM j GROUP BY model")
def read_plan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """8 documents, 2 models, 50 jobs each: 400 jobs a model."""
    docs = corpora.take_n(corpora.lectures(spark, sf_dir).select("doc_id"), 8)
    models = spark.createDataFrame([("block",), ("local",)], "model string")
    return annotate.plan_jobs(docs, models).groupBy("model").agg(F.count("*").alias("jobs"), F.countDistinct("doc_id").alias("docs"), F.sum(F.col("job_id") % 1000).alias("mark"))


# -- significance ----------------------------------------------------------------------------------

MCNEMAR_SQL = """WITH x AS (SELECT doc_id % 2 = 0 AS a, doc_id % 3 = 0 AS b, quality = 1 AS r FROM labels),
c AS (SELECT coalesce(sum(((a = r) AND (b <> r))::INT), 0)::BIGINT AS b, coalesce(sum(((a <> r) AND (b = r))::INT), 0)::BIGINT AS c FROM x)
SELECT b, c, CASE WHEN b + c > 0 THEN round(greatest(abs(b - c) - 1, 0) * greatest(abs(b - c) - 1, 0) / (b + c), 6) ELSE 0 END AS chi2 FROM c"""


@register("sig_mcnemar", MCNEMAR_SQL)
def sig_mcnemar(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = table(spark, sf_dir, "labels").select((F.col("doc_id") % 2 == 0).alias("a"), (F.col("doc_id") % 3 == 0).alias("b"), (F.col("quality") == 1).alias("r"))
    return evaluation.mcnemar(x, "a", "b", "r")


PAIRED_SQL = sentences("F-INT") + f""", m AS (SELECT doc_id, {CUE} AS a, idx % 4 = 3 AS b, ends_para AS r FROM sents WHERE idx < n_sent - 1),
u AS (SELECT doc_id, sum((a AND r)::INT) AS tp_a, sum((a AND NOT r)::INT) AS fp_a, sum((NOT a AND r)::INT) AS fn_a, sum((b AND r)::INT) AS tp_b, sum((b AND NOT r)::INT) AS fp_b, sum((NOT b AND r)::INT) AS fn_b FROM m GROUP BY doc_id)"""
RANDOM_SQL = "WITH " + PAIRED_SQL + """, s AS (SELECT unnest(range(200)) AS seed),
x AS (SELECT seed, substr(md5(doc_id || '-' || seed), 1, 1) < '8' AS w, u.* FROM u, s),
y AS (SELECT seed, sum(CASE WHEN w THEN tp_b ELSE tp_a END) AS ta, sum(CASE WHEN w THEN fp_b + fn_b ELSE fp_a + fn_a END) AS ea, sum(CASE WHEN w THEN tp_a ELSE tp_b END) AS tb, sum(CASE WHEN w THEN fp_a + fn_a ELSE fp_b + fn_b END) AS eb FROM x GROUP BY seed),
o AS (SELECT round(abs(2 * sum(tp_a) / greatest(2 * sum(tp_a) + sum(fp_a + fn_a), 1) - 2 * sum(tp_b) / greatest(2 * sum(tp_b) + sum(fp_b + fn_b), 1)), 9) AS observed FROM u)
SELECT observed, sum((round(abs(2 * ta / greatest(2 * ta + ea, 1) - 2 * tb / greatest(2 * tb + eb, 1)), 9) >= observed)::INT)::BIGINT AS at_least, round((1 + sum((round(abs(2 * ta / greatest(2 * ta + ea, 1) - 2 * tb / greatest(2 * tb + eb, 1)), 9) >= observed)::INT)) / 201, 6) AS p FROM y, o GROUP BY observed"""


def paired(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = scored(corpora.interviews(spark, sf_dir)).withColumn("ref", F.transform("sents", lambda s: s["ends_para"])).withColumn("other", F.transform("sents", lambda s: s["idx"] % 4 == 3))
    a, b = evaluation.array_counts(F.col("positive"), F.col("ref")), evaluation.array_counts(F.col("other"), F.col("ref"))
    rows = docs.where("n_sent > 1").select("doc_id", a.alias("a"), b.alias("b"))
    return rows.select("doc_id", *(F.col(f"{x}.{c}").alias(f"{c}_{x}") for x in "ab" for c in ("tp", "fp", "fn")))


@register("sig_randomization", RANDOM_SQL)
def sig_randomization(spark: SparkSession, sf_dir: str) -> DataFrame:
    return evaluation.randomization(paired(spark, sf_dir), 200)


def _bootstrap_sql(rounds: int) -> str:
    total, steps = 0.0, []
    for k in range(8):
        total += math.exp(-1) / math.factorial(k)
        steps.append(f"(u >= {total!r}::DOUBLE)::INT")
    return "WITH " + PAIRED_SQL + f""", s AS (SELECT unnest(range({rounds})) AS seed),
x AS (SELECT seed, ({sql.h("doc_id || '-' || seed")} % 1048576) / 1048576.0::DOUBLE AS u, u.* FROM u, s),
y AS (SELECT seed, {" + ".join(steps)} AS w, tp_a, fp_a, fn_a, tp_b, fp_b, fn_b FROM x),
z AS (SELECT seed, 2 * sum(w * tp_a) / greatest(sum(w * (2 * tp_a + fp_a + fn_a)), 1) - 2 * sum(w * tp_b) / greatest(sum(w * (2 * tp_b + fp_b + fn_b)), 1) AS d FROM y GROUP BY seed)
SELECT round(avg((d <= 0)::INT), 6) AS p, round(avg(d), 6) AS gain FROM z"""


@register("sig_bootstrap", _bootstrap_sql(200))
def sig_bootstrap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return evaluation.bootstrap(paired(spark, sf_dir), 200)


@register("leak_scan", "SELECT b.item_id, count(d.doc_id)::BIGINT AS docs FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY b.item_id")
def leak_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Evaluation passages that stand verbatim in training text.

    Three whole words from inside a passage are its key; the documents' own runs of three words meet the
    keys by equality, then the whole passage is looked up. Only passages of fewer than five words,
    which have no such key and are rare, are looked up in every document.
    """
    passages = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage"), F.split("text", " ").alias("w"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    keyed = passages.where(F.size("w") >= 5).select("item_id", "passage", F.array_join(F.slice("w", 2, 3), " ").alias("key"))
    runs = F.when(F.size("w") >= 3, F.sequence(F.lit(0), F.size("w") - 3)).otherwise(F.array().cast("array<int>"))
    own = docs.withColumn("w", F.split("text", " ")).select("doc_id", "text", F.explode(F.array_distinct(F.transform(runs, lambda i: F.array_join(F.slice("w", i + 1, 3), " ")))).alias("key"))
    met = own.join(keyed, "key").where(F.contains("text", "passage")).select("item_id", "doc_id")
    short = passages.where((F.size("w") < 5) & (F.length("passage") > 0)).select("item_id", "passage").limit(1001)
    if (n := short.count()) > 1000:
        raise ValueError("more than 1000 passages are too short for a key; the decontamination operator has an automaton for them")
    if n:
        met = met.unionByName(docs.join(F.broadcast(short), F.contains("text", "passage")).select("item_id", "doc_id"))
    return met.groupBy("item_id").agg(F.count("*").alias("docs"))


# -- vectors ---------------------------------------------------------------------------------------


@register("pool_mean", "WITH e AS (SELECT vec_id // 10 AS block, generate_subscripts(embedding, 1) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings), m AS (SELECT block, i, avg(x) AS x FROM e GROUP BY block, i) SELECT block, count(*)::BIGINT AS dims, round(sum(x), 4) AS total, round(sum(x * x), 4) AS norm2 FROM m GROUP BY block")
def pool_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sentence vectors as means of ten token vectors."""
    e = table(spark, sf_dir, "embeddings").select(F.floor(F.col("vec_id") / 10).alias("block"), F.posexplode(F.col("embedding").cast("array<double>")).alias("i", "x"))
    m = e.groupBy("block", "i").agg(F.avg("x").alias("x"))
    return m.groupBy("block").agg(F.count("*").alias("dims"), F.round(F.sum("x"), 4).alias("total"), F.round(F.sum(F.col("x") * F.col("x")), 4).alias("norm2"))


@register("head_prob", "WITH s AS (SELECT vec_id, list_sum(list_transform(range(1, 65), lambda i: embedding[i]::DOUBLE * (CASE WHEN i % 2 = 1 THEN 1 ELSE -1 END))) AS z FROM embeddings) SELECT vec_id, round(1 / (1 + exp(-z)), 6) AS prob, 1 / (1 + exp(-z)) > 0.5 AS is_boundary FROM s")
def head_prob(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-class softmax head on given vectors: the probability is the logistic of the logits' difference."""
    z = F.aggregate(F.transform(F.col("embedding").cast("array<double>"), lambda x, i: F.when(i % 2 == 0, x).otherwise(-x)), F.lit(0.0), lambda a, x: a + x)
    p = 1 / (1 + F.exp(-z))
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(p, 6).alias("prob"), (p > 0.5).alias("is_boundary"))
