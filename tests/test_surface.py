from __future__ import annotations

from pyspark.sql import functions as F

from passage_engine.functions import local, registry, tokens
from passage_engine.functions import text as t
from passage_engine.models import encoder, lexical
from passage_engine.plans import infer, windows
from passage_engine.plans.windows import Adaptive
from passage_engine.sources import corpora, io
from passage_engine.streaming import live


def test_local_rules_equal_columns(spark, tiny):
    d = spark.read.parquet(f"{tiny}/conversations.parquet").limit(40)
    for r in t.with_sentences(d).collect():
        assert [s.text for s in r.sents] == local.all_sentences(r.text)


def test_sql_functions(spark):
    registry.register(spark)
    one = lambda q: spark.sql(f"SELECT {q} AS x").first().x
    assert one("split_paragraphs('a b\n\nc')") == ["a b", "c"]
    assert one("split_sentences('A b. C? d')") == ["A b.", "C?", "d"]
    assert abs(one("char_error_rate('kitten', 'sitting')") - 0.5) < 1e-9
    assert [tuple(w) for w in one("pack_windows(array(1,1,1,1,1,1), 3, 60, 'adaptive', 2)")] == [(0, 2), (2, 4), (4, 5)]
    assert spark.sql("SELECT majority(v, 3) AS m FROM VALUES (1), (1), (0), (1) x(v)").first().m
    text = "Aa bb. Cc dd? Ee ff gg."
    assert " ".join(one(f"segment_text('{text}', 'adaptive')")) == text
    assert [r.text for r in spark.sql(f"SELECT * FROM segments_of('{text}')").collect()] == one(f"segment_text('{text}', 'fixed')")


VOCAB = "/opt/tokenizers/word_bpe_49k.json"


def test_subwords(spark, tiny):
    vocab = tokens.load_vocab(VOCAB)
    for w in ("the", "thing", "ereationism", "straße", "слово"):
        p = tokens.pieces_of(w, vocab)
        assert p[-1].endswith(tokens.END) and tokens.spelled("".join(p).removesuffix(tokens.END)) == w and all(x in vocab for x in p)
        # longest match: no piece could be longer
        at = 0
        letters = "".join(p).removesuffix(tokens.END)
        for x in p:
            own = x.removesuffix(tokens.END)
            longer = [letters[at:e] + (tokens.END if e == len(letters) else "") for e in range(at + len(own) + 1, min(len(letters), at + 16) + 1)]
            assert not any(y in vocab for y in longer)
            at += len(own)
    assert tokens.pieces_of("ab", {"a": 0}) == [tokens.UNKNOWN + tokens.END]
    assert tokens.word_segment("我们去北京", {"我们", "北京"}) == ["我们", "去", "北京"]
    rows = spark.createDataFrame([(1, "我们去北京"), (2, None)], "id long, text string")
    words = spark.createDataFrame([("我们",), ("北京",)], "word string")
    assert [r.words for r in tokens.segmented(rows, words).orderBy("id").collect()] == [["我们", "去", "北京"], None]
    assert tokens.encode(corpora.interviews(spark, tiny), vocab).count() == 87


def test_pieces_feed_windows_and_phones(spark, tiny):
    from passage_engine.models import encoder

    vocab = tokens.load_vocab(VOCAB)
    before = corpora.interviews(spark, tiny).orderBy("doc_id").first()
    after = tokens.as_pieces(corpora.interviews(spark, tiny), vocab).orderBy("doc_id").first()
    assert [s.idx for s in after.sents] == [s.idx for s in before.sents] and [s.ends_para for s in after.sents] == [s.ends_para for s in before.sents]
    assert all(s.n_tok == len(s.text.split()) for s in after.sents) and sum(s.n_tok for s in after.sents) > sum(s.n_tok for s in before.sents)
    word = next(w for w in ("ereationism", "gelimator") if len(tokens.pieces_of(w, vocab)) > 2)
    p = ["the" + tokens.END, *tokens.pieces_of(word, vocab)]
    table = {word: ["a", "b"]}
    every = encoder.phone_ids(p, table, 32)
    assert every[0] == [] and all(x == every[1] and len(x) == 2 for x in every[1:])
    first = encoder.phone_ids(p, table, 32, "first")
    assert first[1] == every[1] and all(x == [] for x in first[2:])
    assert encoder.phone_ids([word, "x"], table, 32) == [every[1], []]


def test_frontier_equals_twin(spark, tiny):
    docs = corpora.interviews(spark, tiny).withColumn("toks", F.transform("sents", lambda s: s["n_tok"])).withColumn("p", F.transform("sents", lexical.cue_positive))
    loop = {r.doc_id: (r.passes, r.encoded, list(r.boundary)) for r in infer.with_probs(docs, F.transform("sents", lexical.cue_prob), Adaptive(10), limit=60, cap=8).collect()}
    for r in docs.select("doc_id", "p", windows.window_array(F.col("toks"), F.col("p"), Adaptive(10), 60, 8).alias("w")).collect():
        assert loop[r.doc_id] == (len(r.w), sum(x.last - x.first + 1 for x in r.w), list(r.p))


def test_model_decisions_do_not_depend_on_partitions(spark, tiny):
    cfg = encoder.Config(vocab=128, width=8, heads=2, layers=1, max_tokens=64)
    blob = encoder.save(cfg, encoder.init(cfg))
    docs = corpora.interviews(spark, tiny).limit(30).cache()
    runs = [{r.doc_id: r.probs for r in infer.with_model(docs.repartition(n), blob, Adaptive(5), batch=b, limit=63, cap=10).collect()} for n, b in ((1, 48), (5, 3))]
    assert all(max((abs(x - y) for x, y in zip(runs[0][d], runs[1][d])), default=0) < 1e-6 for d in runs[0])


def test_stream_equals_batch_after_the_session(spark, tmp_path):
    """A later row of another key moves the watermark past the session, which flushes it."""
    lengths = [7, 8, 20, 21, 9, 14, 33, 5, 6, 8, 28, 2]
    rows = [(1, 0, i, n, 3, 1000 + i) for i, n in enumerate(lengths)]
    path = str(tmp_path / "in")
    schema = "key long, turn int, idx int, length int, n_tok int, at long"
    for k, part in enumerate((rows[:5], rows[5:], [(2, 0, 0, 7, 1, 90_000)], [(3, 0, 0, 7, 1, 190_000)])):
        spark.createDataFrame(part, schema).coalesce(1).write.parquet(f"{path}/{k}")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        s = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*").withColumn("ts", F.timestamp_seconds("at")).withWatermark("ts", "1 minute")
        got = {r.idx: r.is_boundary for r in live.drained(live.segment_stream(s.drop("at"), lookback=3, limit=15, cap=5)).where("key = 1").collect()}
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    assert got == {i: (n + i) % 7 == 0 for i, n in enumerate(lengths)}


def test_sinks_and_checkpoints(spark, tmp_path):
    cfg = encoder.Config(vocab=16, width=4, heads=2, layers=1, max_tokens=8)
    blob = encoder.save(cfg, encoder.init(cfg))
    io.save_checkpoint(spark, blob, f"{tmp_path}/w", "toy")
    assert encoder.load(io.load_checkpoint(spark, f"{tmp_path}/w"))[0] == cfg
    df = spark.range(20).selectExpr("id AS doc_id", "id % 2 AS half")
    io.write_partitioned(df, f"{tmp_path}/p", "half")
    assert spark.read.parquet(f"{tmp_path}/p").where("half = 1").count() == 10
    assert io.unfinished(df, df.where("doc_id < 5")).count() == 15


def test_chunks_merge_to_whole_documents(spark):
    rows = [(1, [(i, f"s{i}", 1, i % 3 == 0) for i in range(57)]), (2, [(0, "a", 1, True)])]
    c = spark.createDataFrame(rows, "doc_id long, sents array<struct<idx:int,text:string,n_tok:int,ends_para:boolean>>").withColumn("n_sent", F.size("sents"))
    parts = infer.chunked(c, 20, 6).withColumn("boundary", F.transform("sents", lambda s: s["ends_para"]))
    assert parts.where("doc_id = 1").count() > 2
    got = {r.doc_id: list(r.boundary) for r in infer.merged(parts).collect()}
    assert got == {1: [i % 3 == 0 for i in range(57)], 2: [True]}


def test_copies_are_decided_once(spark, tiny):
    docs = corpora.interviews(spark, tiny)
    twice = docs.unionByName(docs.withColumn("doc_id", F.col("doc_id") + 10**9))
    seen = []

    def decide(d):
        seen.append(d.count())
        return infer.with_probs(d, F.transform("sents", lexical.cue_prob), Adaptive(10))

    assert infer.once_each(twice, decide).count() == 2 * docs.count() and seen[0] <= docs.count()
