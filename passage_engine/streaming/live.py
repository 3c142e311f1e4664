"""Live transcripts: windows of utterances, late and repeated rows, segmentation with state.

Every stream here ends by itself (``availableNow``), so a query returns a batch DataFrame of what the
stream wrote.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import ArrayType, IntegerType, LongType, StructField, StructType

from ..catalog import register
from ..functions import text as t
from ..plans.windows import MAX_SENTENCES, MAX_TOKENS, Adaptive, fit_last
from ..session import shared_base
from ..sources.corpora import table


def stream(spark: SparkSession, sf_dir: str, name: str, files: int = 1) -> DataFrame:
    """A given table as a file stream; the schema is read from the table, not inferred by the stream."""
    schema = table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "*.parquet").parquet(_folder(sf_dir, name))


def _folder(sf_dir: str, name: str) -> str:
    return f"{sf_dir}/{name}.parquet*"


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to its end into Parquet with a checkpoint, and read the result."""
    spark = df.sparkSession
    place = f"{shared_base(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.outputMode("append").option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).format("parquet").start(f"{place}/out")
    else:

        def put(batch: DataFrame, epoch: int) -> None:
            # each epoch's own folder: a repeated epoch overwrites itself
            batch.write.mode("overwrite").parquet(f"{place}/out/epoch={epoch}")

        q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    if q.exception():
        raise RuntimeError(str(q.exception()))
    if mode == "append":
        return spark.read.schema(df.schema).parquet(f"{place}/out")
    out = spark.read.parquet(f"{place}/out")
    last = out.agg(F.max("epoch")).first()[0]
    return out.where(F.col("epoch") == last).drop("epoch")


def at(df: DataFrame) -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


HOURS = "SELECT event_type, date_trunc('hour', ts) AS start, count(*)::BIGINT AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL"


def tumbling(events: DataFrame) -> DataFrame:
    w = events.groupBy("event_type", F.window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))
    return w.select("event_type", F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "total")


@register("batch_tumbling", HOURS)
def batch_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The batch twin of the tumbling stream."""
    return tumbling(at(table(spark, sf_dir, "events")))


@register("stream_tumbling", HOURS)
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(tumbling(at(stream(spark, sf_dir, "events"))), "complete")


SLIDING = """WITH e AS (SELECT ts, unnest([0, 1]) AS k FROM events), w AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start FROM e) SELECT start, count(*)::BIGINT AS n FROM w GROUP BY start"""


def sliding(events: DataFrame) -> DataFrame:
    return events.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@register("stream_sliding", SLIDING)
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(sliding(at(stream(spark, sf_dir, "events"))), "complete")


SESSION = """WITH g AS (SELECT user_id, ts, value, (coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 30 MINUTE, true))::INT AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k"""


def sessions(events: DataFrame) -> DataFrame:
    return events.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@register("batch_session", SESSION)
def batch_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sessions(at(table(spark, sf_dir, "events")))


@register("stream_session", SESSION)
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drained(sessions(at(stream(spark, sf_dir, "events"))), "complete")


@register("stream_late")
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts in append mode: a window is final once the watermark has passed it."""
    return drained(tumbling(at(stream(spark, sf_dir, "events")).withWatermark("ts", "10 minutes")))


@register("stream_dedup", "SELECT event_id, event_type FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retransmitted rows (each is sent twice here) within the watermark count once."""
    e = at(stream(spark, sf_dir, "events"))
    twice = e.withColumn("sent", F.explode(F.array(F.lit(1), F.lit(2))))
    return drained(twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"))


@register("stream_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream with a static table."""
    return drained(stream(spark, sf_dir, "events").join(table(spark, sf_dir, "customer"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"))


INTERVAL = "SELECT a.event_id AS view_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'"


@register("stream_stream_join", INTERVAL)
def stream_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two streams by key and interval, both with watermarks."""
    a = at(stream(spark, sf_dir, "events")).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("seen")).withWatermark("seen", "1 hour")
    b = at(stream(spark, sf_dir, "events")).where("event_type = 'purchase'").select(F.col("event_id").alias("buy_id"), F.col("user_id").alias("v"), F.col("ts").alias("bought")).withWatermark("bought", "1 hour")
    return drained(a.join(b, F.expr("u = v AND bought >= seen AND bought <= seen + INTERVAL 1 HOUR")).select("view_id", "buy_id"))


STATE = StructType([StructField("start", LongType()), StructField("lengths", ArrayType(IntegerType())), StructField("toks", ArrayType(IntegerType())), StructField("win_no", IntegerType())])
OUT = "key long, idx int, is_boundary boolean, win_no int"


def cue(length: int, idx: int) -> bool:
    """The context-free cue of the batch engine."""
    return (length + idx) % 7 == 0


class LiveSegmenter(StatefulProcessor):
    """Per key: lengths and word counts of the sentences from the present window's start.

    A window runs when the next sentence would exceed its limits; the labels of sentences before the
    next start are final and go out. A session is flushed once the watermark has passed its last row
    by ``gap_ms``.
    """

    def __init__(self, lookback: int = 10, limit: int = MAX_TOKENS, cap: int = MAX_SENTENCES, gap_ms: int = 60_000):
        self.policy, self.limit, self.cap, self.gap = Adaptive(lookback), limit, cap, gap_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("tail", STATE)

    def _windows(self, start: int, lengths: list[int], toks: list[int], win_no: int, flush: bool):
        out = []
        while toks:
            last = fit_last(toks, 0, self.limit, self.cap)
            if last == len(toks) - 1 and not flush:
                break
            decided = [cue(n, start + i) for i, n in enumerate(lengths[: last + 1])]
            end = last == len(toks) - 1
            step = len(toks) if end else self.policy.next_start(0, last, lambda i, d=decided: d[i], len(toks))
            out += [(start + i, decided[i] if i <= last else False, win_no) for i in range(step)]
            start, lengths, toks, win_no = start + step, lengths[step:], toks[step:], win_no + 1
        return out, start, lengths, toks, win_no

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        start, lengths, toks, win_no = (self.state.get() if self.state.exists() else None) or (0, [], [], 0)
        lengths, toks = list(lengths), list(toks)
        came = pd.concat(list(rows)).sort_values(["turn", "idx"], kind="stable")
        lengths += [int(x) for x in came.length]
        toks += [int(x) for x in came.n_tok]
        out, start, lengths, toks, win_no = self._windows(start, lengths, toks, win_no, False)
        self.state.update((start, lengths, toks, win_no))
        for old in self.handle.listTimers():
            self.handle.deleteTimer(old)
        self.handle.registerTimer(int(came.ts.max().timestamp() * 1000) + self.gap)
        if out:
            yield pd.DataFrame([(key[0], *o) for o in out], columns=["key", "idx", "is_boundary", "win_no"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        if self.state.exists():
            start, lengths, toks, win_no = self.state.get()
            out, *_ = self._windows(start, list(lengths), list(toks), win_no, True)
            self.state.clear()
            if out:
                yield pd.DataFrame([(key[0], *o) for o in out], columns=["key", "idx", "is_boundary", "win_no"])

    def close(self) -> None:
        pass


def segment_stream(utterances: DataFrame, **options) -> DataFrame:
    """Utterances (key, ts with a watermark, turn, idx, length, n_tok) to final labels; state is the tail of one window a key."""
    return utterances.groupBy("key").transformWithStateInPandas(LiveSegmenter(**options), OUT, "append", "EventTime")


@register("stream_segment")
def stream_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Live segmentation of the conversations: labels that are final so far."""
    provider = spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        c = stream(spark, sf_dir, "conversations")
        spoken = F.timestamp_seconds(F.col("conv_id") * 600 + F.col("turn") * 10).alias("ts")  # the table has no times
        s = t.with_sentences(c).select(F.col("conv_id").alias("key"), spoken, "turn", F.inline("sents")).select("key", "ts", "turn", "idx", F.length("text").alias("length"), "n_tok")
        return drained(segment_stream(s.withWatermark("ts", "1 minute"), limit=127, cap=20))
    finally:
        if provider:
            spark.conf.set("spark.sql.streaming.stateStore.providerClass", provider)
        else:
            spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
