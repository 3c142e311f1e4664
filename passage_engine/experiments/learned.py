"""Workloads with trained models, at toy width: mechanics and orderings, not published accuracy."""

from __future__ import annotations

from dataclasses import replace
from functools import partial

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import register
from ..functions import phones as ph
from ..functions import pretrain
from ..functions import text as t
from ..functions import tokens
from ..models import encoder, lexical, training
from ..operators import evaluation
from ..plans import infer
from ..plans import windows as win
from ..plans.windows import Adaptive, Fixed
from ..sources import corpora
from ..sources.corpora import table
from .core import scored
from .sql import document_lists, sentences, window_walk, with_

#: Toy sizes: seconds on a laptop, the same code at any width.
TOY = dict(vocab=512, width=16, heads=2, layers=1, max_tokens=128, max_sents=20, context=24)
LIMIT, CAP = 127, 20
EPOCHS, BATCH, RATE, STEPS = 6, 16, 1e-2, 12
#: The larger encoder of the local-context baselines: twice the layers, one and a half times the width.
LARGER = dict(layers=2, width=24)
#: Training documents of the written corpora, which are longer than interviews.
WRITTEN_DOCS = 50
#: Steps of an epoch where all documents train: as many as those of ``WRITTEN_DOCS`` documents gave.
ROUNDS = 20


def planted(corpus: DataFrame, every: int = 1) -> DataFrame:
    """A copy in which the last sentence of a paragraph ends with a marker word three times, so that learning shows.

    ``every`` > 1 plants fewer.
    """
    mark = lambda s: s["ends_para"] & (s["idx"] % every == 0)
    sents = F.transform("sents", lambda s: F.struct(s["idx"].alias("idx"), F.when(mark(s), F.concat(s["text"], F.lit(" finis finis finis"))).otherwise(s["text"]).alias("text"), (s["n_tok"] + 3 * mark(s).cast("int")).alias("n_tok"), s["ends_para"].alias("ends_para")))
    return corpus.withColumn("sents", sents)


def halves(corpus: DataFrame, train_docs: int | None = 150) -> tuple[DataFrame, DataFrame]:
    """A bounded training sample of a corpus (the documented parameter; None: the whole part), and all its held-out documents."""
    part = t.h(t.key(F.col("doc_id"), "half")) % 10
    train, test = corpus.where((part < 8) & (F.col("n_sent") > 1)), corpus.where((part >= 8) & (F.col("n_sent") > 1))
    return train if train_docs is None else corpora.take_n(train, train_docs, 1), test


def trained(train: DataFrame, cfg: encoder.Config, epochs: int = EPOCHS, lexicon: dict | None = None, params: dict | None = None, distributed: bool = False, **options) -> tuple[bytes, list[float]]:
    """Fit on the samples of a bounded number of documents: they fit the driver, where a step takes
    milliseconds; ``distributed`` takes the way of real sizes.
    """
    s = training.samples(train, step=options.pop("step", 10), max_sents=options.pop("max_sents", CAP), limit=LIMIT, **options)
    if distributed:
        s = s.cache()
        try:
            return training.fit(s, cfg, epochs=epochs, batch=BATCH, rate=RATE, lexicon=lexicon, params=params)
        finally:
            s.unpersist()
    return tuned(gathered(s), cfg, epochs, lexicon, params)


def gathered(samples: DataFrame) -> list[tuple[list, list]]:
    return [(r.sents, r.labels) for r in samples.orderBy("doc_id", "first", "version").collect()]


def tuned(rows: list[tuple[list, list]], cfg: encoder.Config, epochs: int = EPOCHS, lexicon: dict | None = None, params: dict | None = None) -> tuple[bytes, list[float]]:
    got, losses = training.fit_local(training.as_blocks([x for x, _ in rows], [y for _, y in rows], cfg, lexicon), cfg, epochs, BATCH, RATE, 0.1, params)
    return encoder.save(cfg, got), losses


def trained_apart(train: DataFrame, cfgs: list[encoder.Config]) -> list[bytes]:
    """``trained`` of several configurations on the same samples, which are drawn once; each fits in a task of its own."""
    rows = gathered(training.samples(train, step=10, max_sents=CAP, limit=LIMIT))
    return [blob for blob, _ in training.apart(train.sparkSession, [partial(tuned, rows, cfg) for cfg in cfgs])]


def judged(blob: bytes, test: DataFrame, policy, lexicon: dict | None = None) -> DataFrame:
    got = infer.with_model(test, blob, policy, lexicon, limit=LIMIT, cap=CAP)
    return got.join(test.select("doc_id", F.transform("sents", lambda s: s["ends_para"]).alias("ref")), "doc_id")


def score_row(blob, test, policy, model: str, corpus: str, lexicon=None) -> DataFrame:
    return evaluation.document_prf(judged(blob, test, policy, lexicon), "boundary", "ref").select(F.lit(model).alias("model"), F.lit(corpus).alias("corpus"), "tp", "fp", "fn", "p", "r", "f1")


def run_rows(runs: list[tuple[bytes, object]], tests: dict[str, DataFrame]) -> DataFrame:
    """Accuracy and work of each run (model, policy) on each corpus, as corpus and place of the run, in one pass.

    A corpus without documents has its rows, too.
    """
    docs = stack([x.select(F.lit(c).alias("corpus"), "doc_id", "sents") for c, x in tests.items()])
    got = infer.with_runs(docs, runs, limit=LIMIT, cap=CAP).withColumn("c", evaluation.array_counts(F.col("boundary"), F.col("ref")))
    sums = got.groupBy("corpus", "run").agg(*(F.sum(f"c.{n}").alias(n) for n in ("tp", "fp", "fn")), F.sum("passes").alias("passes"), F.sum("encoded").cast("long").alias("encoded"), F.avg("nanos").alias("nanos"))
    grid = docs.sparkSession.createDataFrame([(c, r) for c in tests for r in range(len(runs))], "corpus string, run int")
    return evaluation.with_prf(grid.join(sums, ["corpus", "run"], "left").fillna(0, ["tp", "fp", "fn"]))


def named(rows: DataFrame, *names: tuple[str, list]) -> DataFrame:
    """Columns by the place of the run."""
    return rows.withColumns({n: F.get(F.array(*map(F.lit, xs)), F.col("run")) for n, xs in names})


def stack(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


WRITTEN = {"F-EN": corpora.written, "F-COARSE": corpora.coarse}


def _accuracy(kind: str, **extra):
    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = []
        for name, corpus in WRITTEN.items():
            train, test = halves(planted(corpus(spark, sf_dir)), WRITTEN_DOCS)
            blob, _ = trained(train, encoder.Config(kind=kind, **{**TOY, **extra}))
            rows.append(score_row(blob, test, Adaptive(10), kind, f"{name} planted"))
        return stack(rows)

    return build


for _key, _kind, _extra in (("acc_written_block", "block", {}), ("acc_written_local_128", "local", {}), ("acc_written_local_large", "local", LARGER), ("acc_written_local_256", "local", {**LARGER, "context": 48}), ("acc_written_two_level", "two_level", {}), ("acc_written_joint", "two_level", {"joint": True}), ("acc_written_recurrent", "recurrent", {})):
    _f = _accuracy(_kind, **_extra)
    _f.__doc__ = f"Toy-width {_kind} model on planted cues of F-EN and F-COARSE: all held-out documents."
    register(_key)(_f)


@register("acc_written_linear")
def acc_written_linear(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Linear tagger: logistic regression over cohesion, length and position."""

    def features(corpus: DataFrame) -> DataFrame:
        rows = corpus.withColumn("d", lexical.cohesion(F.col("sents"), 3)).select("doc_id", "n_sent", F.inline(F.arrays_zip(F.col("sents").alias("s"), F.col("d").alias("d"))))
        x = F.array(F.col("d"), F.col("s.n_tok") / 20.0, F.col("s.idx") / F.col("n_sent"), F.col("s.text").rlike(r"finis$").cast("double"))
        return rows.select("doc_id", "n_sent", F.col("s.idx").alias("idx"), F.col("s.ends_para").alias("ends_para"), F.col("s.ends_para").cast("double").alias("label"), array_to_vector(x).alias("features"))

    rows = []
    for name, corpus in WRITTEN.items():
        train, test = halves(planted(corpus(spark, sf_dir)), WRITTEN_DOCS)
        model = LogisticRegression(maxIter=20, regParam=0.001).fit(features(train))
        got = model.transform(features(test)).withColumn("is_boundary", vector_to_array("probability")[1] > 0.5)
        rows.append(evaluation.prf(got).withColumn("corpus", F.lit(f"{name} planted")))
    return stack(rows)


@register("fit_distributed")
def fit_distributed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two epochs with gradients summed by the cluster: the loss of each step."""
    train, _ = halves(planted(corpora.interviews(spark, sf_dir)), 40)
    _, losses = trained(train, encoder.Config(**TOY), epochs=2, distributed=True)
    return spark.createDataFrame(list(enumerate(losses)), "step int, loss double")


def sound_words(spark: SparkSession, sf_dir: str) -> dict[str, list[str]]:
    """First pronunciations of the interviews' words, as a checked broadcast."""
    lex = ph.first_entry(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations"))))
    if (n := lex.count()) > 1_000_000:
        raise ValueError(f"a lexicon of {n} words is to be joined, not broadcast")
    return {r.word: list(r.phones) for r in lex.collect()}


#: Kinds of noise and the word rate at which the character error rate of these texts is near 0.16.
NOISE = ("confusion", "filler", "repetition", "deletion")


def spoken(spark: SparkSession, corpus: DataFrame, pairs: DataFrame, rate: float = 0.16) -> DataFrame:
    """A corpus through recognition noise; a sentence that loses all its words stays with an empty text."""
    noisy = ph.corrupt(t.exploded(corpus).select("doc_id", "idx", "text"), pairs, rate, NOISE)
    lists = noisy.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("idx", "hyp"))).alias("hyps"))
    return corpus.join(lists, "doc_id").withColumn("sents", F.zip_with("sents", "hyps", lambda s, x: F.struct(s["idx"].alias("idx"), x["hyp"].alias("text"), t.count_words(x["hyp"]).alias("n_tok"), s["ends_para"].alias("ends_para")))).drop("hyps")


@register("acc_phone_grid")
def acc_phone_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The settings (a) to (d): encoders next and order without and with phones, trained on F-XX; F-XX, F-LEC and F-INT.

    The spoken corpora come through noise at the recognizer's rate of 0.16; all held-out documents are scored.
    """
    words = sound_words(spark, sf_dir)
    pairs = ph.confusions(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations")))).cache()
    train, own = halves(planted(corpora.written(spark, sf_dir, True)), WRITTEN_DOCS)
    tests = {"F-XX": own} | {n: spoken(spark, halves(planted(f(spark, sf_dir)))[1], pairs) for n, f in (("F-LEC", corpora.lectures), ("F-INT", corpora.interviews))}
    rows = []
    for setting, name, extra in (("a", "next", {}), ("b", "next", {"phones": 32}), ("c", "order", {}), ("d", "order", {"phones": 32})):
        cfg = encoder.Config(**TOY, **extra)
        lex = words if extra else None
        blob, _ = trained(train, cfg, lexicon=lex, params=warmed(name, train, cfg)[0])
        rows += [score_row(blob, test, Adaptive(10), f"({setting}) {name}{' + phones' if extra else ''}", corpus, lex) for corpus, test in tests.items()]
    return stack(rows)


@register("acc_phone_pools")
def acc_phone_pools(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean against sum of phone vectors, and words against sub-words, on noisy interviews."""
    words = sound_words(spark, sf_dir)
    pairs = ph.confusions(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations"))))
    train, test = halves(planted(corpora.interviews(spark, sf_dir)))
    test = spoken(spark, test, pairs)
    vocab = tokens.load_vocab(VOCAB)
    rows = []
    for name, extra, cut in (("words", {}, False), ("words, mean", {"phones": 32}, False), ("words, sum", {"phones": 32, "phone_pool": "sum"}, False), ("pieces", {}, True), ("pieces, mean on all", {"phones": 32}, True), ("pieces, mean on first", {"phones": 32, "phone_spread": "first"}, True)):
        lex = words if extra else None
        a, b = (tokens.as_pieces(x, vocab) if cut else x for x in (train, test))
        blob, _ = trained(a, encoder.Config(**TOY, **extra), lexicon=lex)
        rows.append(score_row(blob, b, Adaptive(10), name, "F-INT noisy", lex))
    return stack(rows)


ENCODERS = ("next", "order", "span", "mlm", "rtd")
#: A public vocabulary file; a parameter for users.
VOCAB = "/opt/tokenizers/word_bpe_49k.json"


def warming(name: str, docs: DataFrame, cfg: encoder.Config, most: int = 500) -> list[tuple[int, list[encoder.Block]]]:
    """Samples of an encoder's objective: classes and blocks of each stage.

    Sentence objectives judge the second of two sentences (next: follows or not; order: before, after or
    unrelated; span: swapped or not). Token objectives judge each token: the hidden word among the
    vocabulary's ids (mlm), or whether the generator replaced it (rtd). Order and span add the words
    of shuffled spans. About ``most`` samples, drawn by hash, are used (the documented bound).
    """
    def drawn(df: DataFrame, *key: str) -> list:
        return df.orderBy(F.md5(t.key(*(F.col(k) for k in key), "warm").cast("binary")), *key).limit(most).collect()

    def pairs(df: DataFrame) -> list[encoder.Block]:
        rows = drawn(df, "doc_id", "i")
        sents = [[r.s1.split()[: cfg.max_tokens // 2 - 1], r.s2.split()[: cfg.max_tokens // 2 - 1]] for r in rows]
        blocks = training.as_blocks(sents, None, cfg)
        for blk, r in zip(blocks, rows, strict=True):
            blk.labels = [-1, r.y]
        return blocks

    def units(df: DataFrame, label) -> list[encoder.Block]:
        """Every token is a unit of its own; windows of the model's length cover whole sentences."""
        rows = [(r.x[i : i + cfg.max_tokens - 1], r.target[i : i + cfg.max_tokens - 1], r.y[i : i + cfg.max_tokens - 1]) for r in drawn(df.where(F.size("x") > 0), "doc_id", "idx") for i in range(0, len(r.x), cfg.max_tokens - 1)]
        blocks = training.as_blocks([[[w] for w in x] for x, _, _ in rows], None, cfg)
        for blk, (_, target, y) in zip(blocks, rows, strict=True):
            blk.labels = label(target, y)
        return blocks

    changed = lambda target, y: list(map(int, y))
    hidden = lambda target, y: [i if m else -1 for i, m in zip(encoder.hash_ids(target, cfg.vocab), y, strict=True)]
    return {
        "next": lambda: [(2, pairs(pretrain.next_pairs(docs)))],
        "order": lambda: [(2, units(pretrain.word_order(docs), changed)), (3, pairs(pretrain.order_triples(docs)))],
        "span": lambda: [(2, pairs(pretrain.span_order(docs)))],
        "mlm": lambda: [(cfg.vocab, units(pretrain.mask_tokens(docs), hidden))],
        "rtd": lambda: [(2, units(pretrain.replace_tokens(docs, pretrain.counted_words(docs)), changed))],
    }[name]()


def warm(stages: list[tuple[int, list[encoder.Block]]], cfg: encoder.Config, epochs: int = 2) -> tuple[dict, list[float]]:
    """Parameters after a short pre-training on these stages, and the loss of each epoch."""
    params, losses = encoder.init(cfg), []
    for classes, blocks in stages:
        own = replace(cfg, classes=classes, labels=())
        head = {k: v for k, v in encoder.init(own).items() if k.startswith("head.")}
        got, loss = training.fit_local(blocks, own, epochs, BATCH, RATE, 0.1, params | head)
        params, losses = got, losses + loss
    fresh = encoder.init(cfg)
    return params | {k: fresh[k] for k in ("head.w", "head.b")}, losses


def warmed(name: str, docs: DataFrame, cfg: encoder.Config, epochs: int = 2, most: int = 500) -> tuple[dict, list[float]]:
    """``warm`` on the samples of an objective."""
    return warm(warming(name, docs, cfg, most), cfg, epochs)


def warm_and_tuned(stages: list[tuple[int, list[encoder.Block]]], rows: list[tuple[list, list]], cfg: encoder.Config) -> bytes:
    return tuned(rows, cfg, params=warm(stages, cfg)[0])[0]


@register("pretrain_losses")
def pretrain_losses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss of each pre-training objective by epoch."""
    docs, _ = halves(corpora.interviews(spark, sf_dir))
    docs = docs.cache()
    rows = [(n, e, float(x)) for n in ENCODERS for e, x in enumerate(warmed(n, docs, encoder.Config(**TOY), 3)[1])]
    return spark.createDataFrame(rows, "encoder string, epoch int, loss double")


@register("acc_encoder_grid")
def acc_encoder_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five pre-training objectives, then the same short tuning: F-EN on itself; F-XX on F-XX, F-LEC and F-INT.

    All held-out documents are scored.
    """
    cfg = encoder.Config(**TOY)
    works, grids = [], []
    for own, second, others in (("F-EN", False, {}), ("F-XX", True, {"F-LEC": corpora.lectures, "F-INT": corpora.interviews})):
        train, test = halves(planted(corpora.written(spark, sf_dir, second)), WRITTEN_DOCS)
        train = train.cache()
        grids.append({own: test} | {n: halves(planted(f(spark, sf_dir)))[1] for n, f in others.items()})
        samples = gathered(training.samples(train, step=10, max_sents=CAP, limit=LIMIT))
        works += [partial(warm_and_tuned, warming(name, train, cfg), samples, cfg) for name in ENCODERS]
        train.unpersist()
    blobs = iter(training.apart(spark, works))
    rows = [named(run_rows([(next(blobs), Adaptive(10)) for _ in ENCODERS], tests), ("model", ENCODERS)) for tests in grids]
    return stack(rows).select("model", "corpus", "tp", "fp", "fn", "p", "r", "f1")


@register("acc_gain")
def acc_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Block tagger against local-context classifier on four corpora: F1 of both, gain in points, paired significance."""
    rows = []
    for own, second, others in (("F-EN", False, {}), ("F-XX", True, {"F-LEC": corpora.lectures, "F-INT": corpora.interviews})):
        train, test = halves(planted(corpora.written(spark, sf_dir, second)), WRITTEN_DOCS)
        blobs = {kind: trained(train, encoder.Config(kind=kind, **TOY))[0] for kind in ("block", "local")}
        for corpus, x in ({own: test} | {n: halves(planted(f(spark, sf_dir)))[1] for n, f in others.items()}).items():
            c = {k: judged(b, x, Adaptive(10)).select("doc_id", evaluation.array_counts(F.col("boundary"), F.col("ref")).alias(k)) for k, b in blobs.items()}
            both = c["block"].join(c["local"], "doc_id").cache()
            docs = both.select("doc_id", *(F.col(f"{k}.{n}").alias(f"{n}_{y}") for k, y in (("block", "a"), ("local", "b")) for n in ("tp", "fp", "fn")))
            scores = stack([evaluation.with_prf(both.agg(*(F.sum(f"{k}.{n}").alias(n) for n in ("tp", "fp", "fn")))).withColumn("model", F.lit(k)) for k in blobs])
            pivot = scores.groupBy().pivot("model", ["block", "local"]).agg(F.first("f1"))
            rows.append(pivot.crossJoin(evaluation.gain(scores, "block", "local")).crossJoin(evaluation.randomization(docs, 1000, 1000).select("p")).withColumn("corpus", F.lit(corpus)))
    return stack(rows)


@register("train_policy")
def train_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Training windows by fixed step against adaptive on references: samples and F1."""
    train, test = halves(planted(corpora.interviews(spark, sf_dir)))
    rows = []
    for policy in ("fixed", "reference"):
        blob, _ = trained(train, encoder.Config(**TOY), policy=policy)
        n = training.samples(train, policy, limit=LIMIT, max_sents=CAP).count()
        rows.append(score_row(blob, test, Adaptive(10), policy, "F-INT planted").withColumn("samples", F.lit(n).cast("long")))
    return stack(rows)


@register("dev_grid")
def dev_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Forward step and sentence cap by F1 on all held-out documents: 5, 10, 20 by 20, 40, 60."""
    train, dev = halves(planted(corpora.interviews(spark, sf_dir)), 60)
    train, dev = train.cache(), dev.cache()

    def fit(step, cap):
        return trained(train, encoder.Config(**{**TOY, "max_sents": cap}), epochs=3, step=step, max_sents=cap)[0]

    def judge(blob, cap):
        got = infer.with_model(dev, blob, Adaptive(10), limit=LIMIT, cap=cap)
        ref = dev.select("doc_id", F.transform("sents", lambda s: s["ends_para"]).alias("ref"))
        return float(evaluation.document_prf(got.join(ref, "doc_id"), "boundary", "ref").first().f1)

    found = training.search(fit, judge, (5, 10, 20), (20, 40, 60))
    return spark.createDataFrame(found, "forward_step int, max_sents int, f1 double")


@register("transfer")
def transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Train each model on F-XX, infer on F-XX, F-LEC and F-INT: a grid of models by corpora.

    All documents of the training part train, all held-out documents are scored.
    """
    train, own = halves(planted(corpora.written(spark, sf_dir, True)), None)
    tests = {"F-XX": own, "F-LEC": halves(planted(corpora.lectures(spark, sf_dir)))[1], "F-INT": halves(planted(corpora.interviews(spark, sf_dir)))[1]}
    kinds = ["block", "local", "two_level", "recurrent"]
    samples = training.samples(train, step=10, max_sents=CAP, limit=LIMIT)
    blobs = [b for b, _ in training.fit_all(samples, [encoder.Config(kind=k, **TOY) for k in kinds], EPOCHS, ROUNDS, BATCH, RATE)]
    rows = named(run_rows([(b, Adaptive(10)) for b in blobs], tests), ("model", kinds))
    return rows.groupBy("model").pivot("corpus", list(tests)).agg(F.first("f1"))


@register("sweep_f1")
def sweep_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F1, work and milliseconds a document for steps of both schedules, with the local-context line.

    F-EN, all held-out documents, one trained model of each kind.
    """
    train, test = halves(planted(corpora.written(spark, sf_dir)), WRITTEN_DOCS)
    blob, line = trained_apart(train, [encoder.Config(**TOY), encoder.Config(kind="local", **TOY)])
    runs = [("Local", 1, line, Fixed(1)), *((type(p).__name__, b, blob, p) for b in (1, 2, 5, 10, 15, 20) for p in (Fixed(b), Adaptive(b)))]
    rows = named(run_rows([(model, p) for _, _, model, p in runs], {"F-EN": test}), ("policy", [x[0] for x in runs]), ("step", [x[1] for x in runs]))
    return rows.orderBy("run").select("policy", "step", "p", "r", "f1", "passes", "encoded", F.round(F.col("nanos") / 1e6, 3).alias("ms"))


@register("frontier_equals_twin", with_(sentences("F-INT")) + " SELECT count(DISTINCT doc_id)::BIGINT AS docs, 0::BIGINT AS different FROM sents")
def frontier_equals_twin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of the batched loop against the Column plan, for decisions known in advance: no difference."""
    docs = scored(corpora.interviews(spark, sf_dir))
    loop = infer.with_probs(docs, F.transform("sents", lexical.cue_prob), Adaptive(10)).select("doc_id", "passes", "encoded")
    twin = docs.select("doc_id", win.window_array(F.col("toks"), F.col("positive"), Adaptive(10)).alias("w"))
    both = loop.join(twin, "doc_id")
    size = F.aggregate("w", F.lit(0), lambda a, x: a + x["last"] - x["first"] + 1)
    return both.agg(F.count("*").alias("docs"), F.sum(((F.col("passes") != F.size("w")) | (F.col("encoded") != size)).cast("long")).alias("different"))


@register("phone_closeness")
def phone_closeness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cosine of words that sound alike less that of others, before and after tuning, without and with phones."""
    cfg = encoder.Config(**TOY, phones=32)
    train, _ = halves(planted(corpora.interviews(spark, sf_dir)))
    words = sound_words(spark, sf_dir)
    before = encoder.init(cfg)
    after = encoder.load(trained(train, cfg, lexicon=words)[0])[1]
    lex = ph.first_entry(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations"))))

    def vectors(params: dict, phones: bool):
        sent = spark.sparkContext.broadcast((params["tok"], params["phone"]))

        def run(frames):
            tok, phone = sent.value
            for pdf in frames:
                v = tok[encoder.hash_ids(pdf.word.tolist(), cfg.vocab)]
                if phones:
                    symbols = encoder.phone_ids(pdf.word.tolist(), dict(zip(pdf.word, pdf.phones, strict=True)), cfg.phones)
                    v = v + [phone[s].mean(axis=0) if s else 0 * phone[0] for s in symbols]
                yield pdf[["word", "phone_key"]].assign(v=list(v))

        return lex.mapInPandas(run, "word string, phone_key string, v array<double>")

    grid = [(when, what, params, x) for when, params in (("before", before), ("after", after)) for what, x in (("words", False), ("words and phones", True))]
    return stack([ph.closeness(vectors(params, x)).select(F.lit(when).alias("tuning"), F.lit(what).alias("vectors"), F.round("same", 4).alias("same"), F.round("other", 4).alias("other"), F.round("closeness", 4).alias("closeness")) for when, what, params, x in grid])


def _sizes_sql() -> str:
    """The published sizes by the layers' shapes: tables, norms, four square maps and two wide ones a layer, head."""
    rows = ", ".join(f"('{n}', {c.vocab}, {c.max_tokens}, {c.width}, {c.layers})" for n, c in (("base", encoder.BASE), ("large", encoder.LARGE)))
    return f"""WITH d AS (SELECT len(string_split(text, ' '))::HUGEINT AS t FROM conversations WHERE text IS NOT NULL)
SELECT model, ((v + m + 2) * w + 2 * w + l * (4 * (w * w + w) + 8 * w * w + 5 * w + 4 * w) + 2 * w + 2)::BIGINT AS params, l::INT AS layers, w::INT AS width,
sum(l * (24 * t * w * w + 4 * t * t * w))::DOUBLE AS flops FROM d, (VALUES {rows}) x(model, v, m, w, l) GROUP BY model, v, m, w, l"""


@register("model_sizes", _sizes_sql())
def model_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parameters of the published base and large sizes, and work of one pass for each turn of the conversations.

    A turn's work is a whole number below 2^53, and the sum is exact.
    """
    rows = [(n, encoder.n_params(c), c.layers, c.width) for n, c in (("base", encoder.BASE), ("large", encoder.LARGE))]
    models = spark.createDataFrame(rows, "model string, params long, layers int, width int")
    turns = table(spark, sf_dir, "conversations").where("text is not null").select(F.size(F.split("text", " ")).cast("long").alias("t"))
    work = evaluation.flops(F.col("t"), F.col("layers"), F.col("width")).cast("decimal(28,0)")
    return turns.crossJoin(F.broadcast(models)).groupBy("model", "params", "layers", "width").agg(F.sum(work).cast("double").alias("flops"))


MARKS = ("", ",", ".", "?")


def words_as_sentences(corpus: DataFrame) -> DataFrame:
    """Every word becomes a unit of its own: breaks are then judged at each token, not each sentence.

    Labels are the sentences' boundaries at their last words.
    """
    units = F.flatten(F.transform("sents", lambda s: F.transform(F.split(s["text"], t.SPACE), lambda w, i: F.struct(w.alias("text"), (s["ends_para"] & (i == s["n_tok"] - 1)).alias("ends_para")))))
    sents = F.transform(units, lambda u, i: F.struct(i.alias("idx"), u["text"].alias("text"), F.lit(1).alias("n_tok"), u["ends_para"].alias("ends_para")))
    return corpus.withColumn("sents", sents).withColumn("n_sent", F.size("sents"))


@register("acc_local_tokens")
def acc_local_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The local-context classifier with a candidate break at every token."""
    train, test = (words_as_sentences(x) for x in halves(planted(corpora.interviews(spark, sf_dir)), 30))
    blob, _ = trained(train, encoder.Config(kind="local", **TOY), epochs=3, max_sents=40)
    return score_row(blob, test, Adaptive(10), "local, tokens", "F-INT planted")


def word_windows(docs: DataFrame, size: int = 100) -> DataFrame:
    """Every word of every document, in windows of ``size`` that don't overlap: (doc_id, first, s)."""
    starts = F.sequence(F.lit(0), F.size("sents") - 1, F.lit(size))
    return docs.where(F.size("sents") > 0).select("doc_id", F.explode(starts).alias("first"), "sents").select("doc_id", "first", F.slice("sents", F.col("first") + 1, size).alias("s"))


@register("punct_model")
def punct_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Punctuation restoring by the encoder with a four-class head on single words: none , . ?

    Turns are cut into windows of 100 words. 40 turns train; all windows of all held-out turns are scored.
    """
    docs = words_as_sentences(corpora.interviews(spark, sf_dir))
    rows = word_windows(docs).withColumn("version", F.lit("whole"))
    mark = lambda w: F.when(w.endswith(","), 1).when(w.rlike("[.!]$"), 2).when(w.endswith("?"), 3).otherwise(0)
    rows = rows.select("doc_id", "first", "version", F.transform("s", lambda x: F.array(F.regexp_replace(x["text"], "[.!?,]+$", ""))).alias("sents"), F.transform("s", lambda x: mark(x["text"])).alias("labels"))
    chosen = corpora.take_n(docs.where("doc_id % 10 < 8"), 40, 1).select("doc_id")
    train, test = rows.join(chosen, "doc_id", "left_semi").cache(), rows.where("doc_id % 10 >= 8")
    cfg = encoder.Config(**{**TOY, "max_sents": 100}, classes=len(MARKS), labels=MARKS)
    blob, _ = training.fit(train, cfg, epochs=2, rate=RATE, max_steps=STEPS)
    train.unpersist()
    sent = spark.sparkContext.broadcast(blob)

    def run(frames):
        c, p = encoder.load(sent.value)
        net = encoder.Network(c, p)
        for pdf in frames:
            said = []
            for i in range(0, len(pdf), 32):
                z, real, _ = net.logits(training.as_blocks(pdf.sents.iloc[i : i + 32], None, c))
                said += [list(map(int, r.argmax(axis=-1)[ok])) for r, ok in zip(z.value, real, strict=True)]
            yield pdf[["doc_id", "labels"]].assign(said=said)

    got = test.mapInPandas(run, "doc_id long, labels array<int>, said array<int>")
    return evaluation.document_prf(got.select(F.transform("said", lambda x: x > 0).alias("p"), F.transform("labels", lambda x: x > 0).alias("r")), "p", "r")


@register("acc_pk")
def acc_pk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pk and window difference of the cohesion baseline, k = 3."""
    docs = corpora.written(spark, sf_dir).where("n_sent > 3")
    x = docs.select(lexical.cohesion_positive(F.col("sents")).alias("p"), F.transform("sents", lambda s: s["ends_para"]).alias("r"))
    return x.agg(F.round(F.avg(evaluation.pk(F.col("p"), F.col("r"), 3)), 4).alias("pk"), F.round(F.avg(evaluation.window_diff(F.col("p"), F.col("r"), 3)), 4).alias("window_diff"))


@register("noise_calibrated")
def noise_calibrated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The word rate at which the character error rate is near 16 per cent."""
    rows = t.exploded(corpora.interviews(spark, sf_dir)).select("doc_id", "idx", "text").cache()
    pairs = ph.confusions(ph.lexicon(ph.vocabulary(table(spark, sf_dir, "conversations")))).cache()
    rate, cer = ph.calibrated_rate(rows, pairs)
    return spark.createDataFrame([(round(rate, 4), cer)], "word_rate double, cer double")


@register("infer_distinct", with_(sentences("F-INT"), document_lists(), window_walk("VALUES ('adaptive', 10)")) + " SELECT (SELECT count(DISTINCT doc_id) FROM sents)::BIGINT AS docs, (SELECT count(*) FROM sents)::BIGINT AS sents, count(*)::BIGINT AS passes FROM walk")
def infer_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies are decided once; every document has its result."""
    docs = corpora.interviews(spark, sf_dir)
    got = infer.once_each(docs, lambda d: infer.with_probs(d, F.transform("sents", lexical.cue_prob), Adaptive(10)))
    return got.agg(F.count("*").alias("docs"), F.sum("n_sent").alias("sents"), F.sum("passes").alias("passes"))
