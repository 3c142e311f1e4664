"""Fine tuning: samples to gradients in tasks, Adam on the driver."""

from __future__ import annotations

from collections.abc import Callable
from itertools import groupby

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as t
from ..plans import windows as win
from ..session import own_folder
from .encoder import Adam, Block, Config, Network, hash_ids, init, load, phone_ids, save

SAMPLE = "doc_id long, first int, sents array<array<string>>, labels array<int>"


def samples(corpus: DataFrame, policy: str = "fixed", step: int = 10, max_sents: int = 60, limit: int = 511, overlong: str = "both", lookback: int = 10, keep_partial: bool = False) -> DataFrame:
    """Training samples of a corpus: (doc_id, first, version, sents: words of each sentence, labels).

    policy 'fixed' steps forward, 'reference' follows the adaptive schedule on the references.
    Samples beyond the token limit come cut, trimmed or both. Where a cut falls inside a sentence, its
    part goes with its label, or stays with it (``keep_partial``).
    """
    rows = corpus.select("doc_id", "n_sent", F.transform("sents", lambda s: F.split(s["text"], t.SPACE)).alias("w"), F.transform("sents", lambda s: s["n_tok"]).alias("n"), F.transform("sents", lambda s: s["ends_para"]).alias("r"))
    if policy == "fixed":
        wins = win.forward_windows(F.col("n_sent"), step, max_sents)
    else:
        wins = win.reference_windows(F.col("n"), F.col("r"), lookback, limit, max_sents)
    cutout = lambda c: F.slice(c, F.col("first") + 1, F.col("last") - F.col("first") + 1)
    s = rows.select("doc_id", "w", "n", "r", F.inline(wins)).select("doc_id", "first", cutout(F.col("w")).alias("w"), cutout(F.col("n")).alias("n"), F.transform(cutout(F.col("r")), lambda x: x.cast("int")).alias("y"))
    total = F.aggregate("n", F.lit(0), lambda a, x: a + x)
    version = {"cut": F.struct(F.lit("cut").alias("version"), win.cut(F.col("n"), limit, keep_partial).alias("keep")), "trim": F.struct(F.lit("trim").alias("version"), win.trim(F.col("n"), limit).alias("keep"))}
    chosen = F.array(*(version[v] for v in (("cut", "trim") if overlong == "both" else (overlong,))))
    whole = F.array(F.struct(F.lit("whole").alias("version"), F.col("n").alias("keep")))
    s = s.select("doc_id", "first", "w", "y", F.inline(F.when(total > limit, chosen).otherwise(whole)))
    kept = F.zip_with(F.slice("w", 1, F.size("keep")), F.col("keep"), lambda ws, k: F.slice(ws, 1, k))
    return s.select("doc_id", "first", "version", kept.alias("sents"), F.slice("y", 1, F.size("keep")).alias("labels"))


def as_blocks(sents, labels, cfg: Config, lexicon: dict | None = None) -> list[Block]:
    out = []
    for ss, ys in zip(sents, labels if labels is not None else [None] * len(sents), strict=True):
        ws = [list(s) for s in ss]
        out.append(Block([hash_ids(w, cfg.vocab) for w in ws], [phone_ids(w, lexicon, cfg.phones, cfg.phone_spread) for w in ws] if cfg.phones and lexicon is not None else None, None if ys is None else [int(y) for y in ys]))
    return out


def gradients(blocks: list[Block], cfg: Config, params: dict, dropout: float, seed: int) -> tuple[dict, float, int]:
    net = Network(cfg, params, train=True, dropout=dropout, seed=seed)
    loss, n = net.loss(blocks)
    loss.backward()
    return {k: v.grad for k, v in net.p.items() if v.grad is not None}, float(loss.value), n


def fit_local(blocks: list[Block], cfg: Config, epochs: int = 2, batch: int = 48, rate: float = 5e-5, dropout: float = 0.1, params: dict | None = None) -> tuple[dict, list[float]]:
    """The same steps on one machine, for toy widths and tests."""
    params, adam, losses = dict(params or init(cfg)), Adam(rate), []
    for e in range(epochs):
        order = np.random.default_rng(cfg.seed + e).permutation(len(blocks))
        total = n_all = 0
        for i in range(0, len(order), batch):
            g, loss, n = gradients([blocks[k] for k in order[i : i + batch]], cfg, params, dropout, cfg.seed * 1000 + e * 100 + i)
            adam.step(params, {k: v / max(1, n) for k, v in g.items()})
            total, n_all = total + loss, n_all + n
        losses.append(total / max(1, n_all))
    return params, losses


def apart(spark: SparkSession, works: list[Callable[[], object]]) -> list:
    """What each of a few works returns; every one runs in a task of its own, so models are fitted at the same time."""
    return spark.sparkContext.parallelize(range(len(works)), len(works)).map(lambda i: works[i]()).collect()


def _added(a: pd.DataFrame) -> pd.DataFrame:
    """Rows (g, loss, n) summed to one."""
    if not len(a):
        return a
    total = np.frombuffer(a.g.iloc[0]).copy()
    for g in a.g.iloc[1:]:
        total += np.frombuffer(g)
    return pd.DataFrame({"g": [total.tobytes()], "loss": [a.loss.sum()], "n": [a.n.sum()]})


def summed(rows: DataFrame, parts: int, fan: int = 16, *by: str) -> DataFrame:
    """Gradients (g, loss, n), one row a task, to one row (of each value of ``by``), by levels of at most ``fan`` rows a group."""
    names = [*by, "g", "loss", "n"]
    while parts > 1:
        parts = -(-parts // fan)
        rows = rows.withColumn("k", F.pmod(F.monotonically_increasing_id() + F.shiftright(F.monotonically_increasing_id(), 33), F.lit(parts)).cast("int")).groupBy(*by, "k").applyInPandas(lambda pdf: _added(pdf[["g", "loss", "n"]]).assign(**{b: pdf[b].iloc[0] for b in by})[names], "".join(f"{b} int, " for b in by) + "g binary, loss double, n long")
    return rows


def _descend(adam: Adam, params: dict, got: list) -> float | None:
    """Adam's step by summed gradients (g, loss, n), and the loss of a decision; None without any."""
    if not (total := sum(r.n for r in got)):
        return None
    flat = sum(np.frombuffer(r.g) for r in got) / total
    grads, at = {}, 0
    for x in sorted(params):
        grads[x] = flat[at : at + params[x].size].reshape(params[x].shape)
        at += params[x].size
    adam.step(params, grads)
    return sum(r.loss for r in got) / total


def fit(train: DataFrame, cfg: Config, epochs: int = 2, batch: int = 48, rate: float = 5e-5, dropout: float = 0.1, lexicon: dict | None = None, params: dict | None = None, max_steps: int | None = None, folder: str | None = None) -> tuple[bytes, list[float]]:
    """Synchronous mini-batches of ``batch`` samples drawn by hash, gradients summed by the cluster.

    The samples are written once to ``folder`` (default: below spark.checkpoint.dir), partitioned by
    the step of the first epoch; a later epoch reads the steps in another order, so each step reads
    its own files alone. Each task sums its gradients to one row, the rows meet in a tree; the driver
    receives one row a step and holds one set of parameters, never samples. Every step's draw depends
    on ids alone, so a retried task repeats itself. ``max_steps`` bounds the steps of an epoch.
    """
    spark = train.sparkSession
    n = train.count()
    steps = max(1, -(-n // batch))
    draw = F.pmod(t.h(t.key(F.col("doc_id"), F.col("first"), F.col("version"), "step")), F.lit(steps)).cast("int")
    path = own_folder(spark, folder)
    used = list(range(min(steps, max_steps or steps)))
    train.withColumn("step", draw).where(F.col("step") < len(used)).select("step", "sents", "labels").repartition(max(1, min(len(used), int(spark.conf.get("spark.sql.shuffle.partitions")))), "step").write.partitionBy("step").parquet(path)
    stored = spark.read.schema("sents array<array<string>>, labels array<int>, step int").parquet(path)
    params, adam, losses = dict(params or init(cfg)), Adam(rate), []
    names = sorted(params)
    lex = spark.sparkContext.broadcast(lexicon)
    for e in range(epochs):
        for s in np.random.default_rng(cfg.seed + e).permutation(used).tolist() if e else used:
            sent = spark.sparkContext.broadcast(save(cfg, params))

            def run(frames, sent=sent, e=e, s=s):
                c, p = load(sent.value)
                flat, loss, count = None, 0.0, 0
                for pdf in frames:
                    if len(pdf):
                        g, own, k = gradients(as_blocks(pdf.sents, pdf.labels, c, lex.value), c, p, dropout, c.seed * 7919 + e * 101 + s)
                        one = np.concatenate([np.asarray(g.get(x, np.zeros_like(p[x]))).ravel() for x in names])
                        flat, loss, count = one if flat is None else flat + one, loss + own, count + k
                if flat is not None:
                    yield pd.DataFrame({"g": [flat.tobytes()], "loss": [loss], "n": [count]})

            rows = stored.where(F.col("step") == s).select("sents", "labels")
            parts = rows.rdd.getNumPartitions()
            got = summed(rows.mapInPandas(run, "g binary, loss double, n long"), parts).collect()
            sent.destroy()
            if (loss := _descend(adam, params, got)) is not None:
                losses.append(loss)
    return save(cfg, params), losses


def fit_all(train: DataFrame, cfgs: list[Config], epochs: int = 2, steps: int = 20, batch: int = 16, rate: float = 5e-5, dropout: float = 0.1, lexicon: dict | None = None, folder: str | None = None, piece: int = 4) -> list[tuple[bytes, list[float]]]:
    """Several models on the same samples, any number of them: every epoch goes through all.

    An epoch has a step for every ``batch`` samples, at most ``steps``; beyond that a step's batch grows, so the
    jobs are of a bounded number and each keeps all tasks busy. Samples are dealt by hash to slices of about
    ``piece``, slices to steps. A task goes through its slices one by one and sums each model's gradients to
    one row; the driver receives at most sixteen rows a model and step, never samples.
    """
    spark = train.sparkSession
    if not (n := train.count()):
        return [(save(cfg, init(cfg)), []) for cfg in cfgs]
    slices, steps = -(-n // piece), min(steps, -(-n // batch))
    drawn = train.withColumn("slice", F.pmod(t.h(t.key(F.col("doc_id"), F.col("first"), F.col("version"), "slice")), F.lit(slices)).cast("int")).withColumn("step", F.col("slice") % steps)
    path = own_folder(spark, folder)
    shares = max(1, min(slices // steps, 2 * spark.sparkContext.defaultParallelism))
    drawn.repartitionById(shares, F.pmod(F.floor(F.col("slice") / steps), F.lit(shares)).cast("int")).sortWithinPartitions("step", "slice", "doc_id", "first", "version").select("step", "slice", "sents", "labels").write.partitionBy("step").parquet(path)
    stored = spark.read.schema("slice int, sents array<array<string>>, labels array<int>, step int").parquet(path)
    parts, models = {}, [(init(cfg), Adam(rate), []) for cfg in cfgs]
    lex = spark.sparkContext.broadcast(lexicon)
    for e in range(epochs):
        for s in np.random.default_rng(cfgs[0].seed + e).permutation(steps).tolist():
            sent = spark.sparkContext.broadcast([save(cfg, params) for cfg, (params, _, _) in zip(cfgs, models, strict=True)])

            def run(frames, sent=sent, e=e):
                nets = [load(blob) for blob in sent.value]
                flat, loss, count = [0.0] * len(nets), [0.0] * len(nets), [0] * len(nets)
                samples = (x for pdf in frames for x in zip(pdf.slice.tolist(), pdf.sents, pdf.labels, strict=True))
                for k, own in groupby(samples, key=lambda x: x[0]):
                    _, sents, labels = zip(*own, strict=True)
                    for m, (c, p) in enumerate(nets):
                        g, mine, decided = gradients(as_blocks(sents, labels, c, lex.value), c, p, dropout, c.seed * 7919 + e * 1_000_003 + k)
                        flat[m] = flat[m] + np.concatenate([np.asarray(g.get(x, np.zeros_like(p[x]))).ravel() for x in sorted(p)])
                        loss[m], count[m] = loss[m] + mine, count[m] + decided
                if any(count):
                    yield pd.DataFrame({"m": range(len(nets)), "g": [x.tobytes() for x in flat], "loss": loss, "n": count})

            rows = stored.where(F.col("step") == s).select("slice", "sents", "labels")
            if s not in parts:
                parts[s] = rows.rdd.getNumPartitions()
            rows = rows.mapInPandas(run, "m int, g binary, loss double, n long")
            got = (summed(rows, parts[s], 16, "m") if parts[s] > 16 else rows).collect()
            sent.destroy()
            for m, (params, adam, losses) in enumerate(models):
                if (x := _descend(adam, params, [r for r in got if r.m == m])) is not None:
                    losses.append(x)
    return [(save(cfg, params), losses) for cfg, (params, _, losses) in zip(cfgs, models, strict=True)]


def search(train_of, dev_score, steps=(5, 10, 20), max_sents=(20, 40, 60)) -> list[tuple[int, int, float]]:
    """Grid over forward step and sentence cap by the score on held-out documents, best first."""
    found = [(s, m, dev_score(train_of(s, m), m)) for s in steps for m in max_sents]
    return sorted(found, key=lambda x: (-x[2], x[0], x[1]))
