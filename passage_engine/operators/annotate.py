"""Paragraph annotation: assignment, screening, leave-one-out scores, voting, agreement."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as t
from .evaluation import counts, with_prf

#: Per cent of references that the synthetic annotators flip.
RATES = (5, 10, 15, 25, 40)


def assign(sentences: DataFrame, annotators: DataFrame, k: int = 5) -> DataFrame:
    """k annotators for each sentence, by hash order; annotators (annotator) is a small table."""
    w = Window.partitionBy("doc_id", "idx").orderBy(t.h(t.key(F.col("doc_id"), F.col("idx"), F.col("annotator"))), "annotator")
    return sentences.crossJoin(F.broadcast(annotators)).withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).drop("r")


def synthetic_votes(sentences: DataFrame, rates: tuple[int, ...] = RATES) -> DataFrame:
    """(doc_id, idx, ends_para) to votes of annotators 1..n that flip the reference at their rates."""
    rows = sentences.select("*", F.posexplode(F.array(*map(F.lit, rates))).alias("a", "rate")).withColumn("annotator", F.col("a") + 1)
    flip = t.h(t.key(F.col("doc_id"), F.col("idx"), F.col("annotator"))) % 100 < F.col("rate")
    return rows.withColumn("vote", (F.col("ends_para") != flip).cast("int")).drop("a", "rate")


def f1(votes: DataFrame, *by: str) -> DataFrame:
    """Positive P/R/F1 of votes against ends_para, last sentences left out."""
    return with_prf(votes.groupBy(*by).agg(*counts(F.col("vote") == 1, F.col("ends_para"), F.col("idx") < F.col("n_sent") - 1)))


def screen(votes: DataFrame, min_f1: float = 60.0) -> DataFrame:
    """Annotators whose F1 in per cent on formal text exceeds the bound."""
    return f1(votes, "annotator").where(F.col("f1") * 100 > min_f1)


def leave_one_out(votes: DataFrame, rank_by: str = "doc") -> DataFrame:
    """Each annotator's F1 against the majority of the others, by document or over all, with its rank.

    The others' total is the sentence's total less the own vote: a window sum, no self join. More
    than half of the others make a positive.
    """
    sentence = Window.partitionBy("doc_id", "idx")
    others = F.sum("vote").over(sentence) - F.col("vote")
    n = F.count("*").over(sentence) - 1
    rows = votes.withColumn("peer", 2 * others > n)
    by = ["doc_id", "annotator"] if rank_by == "doc" else ["annotator"]
    scores = with_prf(rows.groupBy(*by).agg(*counts(F.col("vote") == 1, F.col("peer"))))
    order = Window.partitionBy(*by[:-1]).orderBy(F.desc("f1"), "annotator") if rank_by == "doc" else Window.partitionBy(F.lit(0)).orderBy(F.desc("f1"), "annotator")
    return scores.withColumn("rank", F.row_number().over(order))


def vote(votes: DataFrame, keep: int = 4, need: int = 3, rank_by: str = "doc") -> DataFrame:
    """Decision for each sentence: at least ``need`` positives among the ``keep`` best annotators."""
    best = leave_one_out(votes, rank_by).where(F.col("rank") <= keep).select(*(["doc_id", "annotator"] if rank_by == "doc" else ["annotator"]))
    kept = votes.join(best, best.columns, "left_semi")
    return kept.groupBy("doc_id", "idx").agg((F.sum("vote") >= need).alias("is_boundary"))


def majority(votes: DataFrame, need: int = 3) -> DataFrame:
    """Decision on all votes."""
    return votes.groupBy("doc_id", "idx").agg((F.sum("vote") >= need).alias("is_boundary"))


def agreement(votes: DataFrame) -> DataFrame:
    """Share of sentences whose votes are all alike."""
    each = votes.groupBy("doc_id", "idx").agg((F.min("vote") == F.max("vote")).cast("int").alias("same"))
    return each.agg(F.count("*").alias("sentences"), F.sum("same").cast("long").alias("same")).withColumn("share", F.round(F.col("same") / F.col("sentences"), 6))


def effective(returns: DataFrame, low: float = 6.0, high: float = 20.0, questions: int | None = None) -> DataFrame:
    """Returns of jobs with all questions answered within the times, both ends kept, by workers of one model only."""
    jobs = returns.groupBy("job_id", "model", "worker_id").agg(F.max("minutes").alias("most"), F.min("minutes").alias("least"), F.count("correct").alias("answers"), F.count("*").alias("asked"))
    single = returns.groupBy("worker_id").agg(F.min("model").alias("x"), F.max("model").alias("y")).where("x = y").select("worker_id")
    full = F.col("answers") == (F.col("asked") if questions is None else F.lit(questions))
    good = jobs.where(full & (F.col("least") >= low) & (F.col("most") <= high)).join(single, "worker_id", "left_semi").select("job_id", "model")
    return returns.join(good, ["job_id", "model"], "left_semi")


def answer_accuracy(returns: DataFrame, low: float = 6.0, high: float = 20.0) -> DataFrame:
    """Effective jobs, answers and the share of right ones for each model."""
    return effective(returns, low, high).groupBy("model").agg(F.countDistinct("job_id").alias("jobs"), F.count("*").alias("answers"), F.round(F.avg("correct"), 6).alias("accuracy"))


def plan_jobs(docs: DataFrame, models: DataFrame, jobs: int = 50) -> DataFrame:
    """Every document in every model's segmentation, ``jobs`` times: (job_id, doc_id, model, copy)."""
    copies = docs.sparkSession.range(jobs).select(F.col("id").cast("int").alias("copy"))
    rows = docs.select("doc_id").crossJoin(F.broadcast(models)).crossJoin(F.broadcast(copies))
    return rows.withColumn("job_id", t.h(t.key(F.col("doc_id"), F.col("model"), F.col("copy"))))


def model_of_worker(worker: Column, models: list[str]) -> Column:
    """Each worker sees one model, by hash."""
    return F.element_at(F.array(*map(F.lit, models)), (t.h(worker) % len(models) + 1).cast("int"))
