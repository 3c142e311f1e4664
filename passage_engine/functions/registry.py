"""Public functions for SQL: scalar UDFs over Arrow batches, grouped aggregates, a table function.

Hot paths use the Column expressions; these serve users who write SQL text.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T

from pyspark.sql.functions import pandas_udf, udtf

from ..plans.windows import Adaptive, Fixed, trace
from . import local

# types as objects: a session isn't there yet when this is imported
STRINGS = T.ArrayType(T.StringType())
WINDOWS = T.ArrayType(T.StructType([T.StructField("first", T.IntegerType()), T.StructField("last", T.IntegerType())]))

@pandas_udf(STRINGS)
def split_paragraphs(text: pd.Series) -> pd.Series:
    return text.map(lambda t: local.paragraphs(t or ""))


@pandas_udf(STRINGS)
def split_sentences(text: pd.Series) -> pd.Series:
    return text.map(lambda t: local.sentences(t or ""))


@pandas_udf(T.ArrayType(T.DoubleType()))
def boundary_probs(text: pd.Series) -> pd.Series:
    return text.map(lambda t: [local.cue(s, i) for i, s in enumerate(local.all_sentences(t or ""))])


@pandas_udf(STRINGS)
def segment_text(text: pd.Series, policy: pd.Series) -> pd.Series:
    """Paragraph strings by the context-free cue; policy: 'fixed' or 'adaptive'.

    Decisions of this cue don't depend on the schedule, so both give the same paragraphs.
    """
    return pd.Series([local.segmented(t or "") for t in text])


@pandas_udf(WINDOWS)
def pack_windows(n_tok: pd.Series, limit: pd.Series, cap: pd.Series, policy: pd.Series, b: pd.Series) -> pd.Series:
    """Windows of token counts when no sentence is positive."""

    def one(n, li, c, p, k):
        rule = Fixed(int(k)) if p == "fixed" else Adaptive(int(k))
        return [{"first": a, "last": z} for a, z in trace(list(map(int, n)), lambda i: False, rule, int(li), int(c))] if len(n) else []

    return pd.Series([one(*x) for x in zip(n_tok, limit, cap, policy, b, strict=True)])


@pandas_udf(T.DoubleType())
def char_error_rate(ref: pd.Series, hyp: pd.Series) -> pd.Series:
    return pd.Series([local.edits(r or "", h or "") / max(1, len(r or "")) for r, h in zip(ref, hyp, strict=True)])


@pandas_udf(T.DoubleType())
def boundary_f1(pred: pd.Series, ref: pd.Series) -> float:
    """F1 of a group's rows; leave the last sentences out by a filter."""
    tp, fp, fn = int((pred & ref).sum()), int((pred & ~ref).sum()), int((~pred & ref).sum())
    return 2 * tp / (2 * tp + fp + fn) if tp + fp + fn else 0.0


@pandas_udf(T.BooleanType())
def majority(vote: pd.Series, need: pd.Series) -> bool:
    return bool(vote.sum() >= need.iloc[0])


@udtf(returnType=T.StructType([*(T.StructField(n, T.IntegerType()) for n in ("seg_no", "first", "last")), T.StructField("text", T.StringType())]))
class SegmentsOf:
    """Segments of one text by the context-free cue."""

    def eval(self, text: str):
        ss = local.all_sentences(text or "")
        first = no = 0
        for i, s in enumerate(ss):
            if i == len(ss) - 1 or local.cue(s, i) > 0.5:
                yield no, first, i, " ".join(ss[first : i + 1])
                no, first = no + 1, i + 1


FUNCTIONS = {f: globals()[f] for f in ("split_paragraphs", "split_sentences", "boundary_probs", "segment_text", "pack_windows", "char_error_rate", "boundary_f1", "majority")}


def register(spark: SparkSession) -> None:
    """Make all public functions known to SQL."""
    from . import phones as ph

    for name, f in FUNCTIONS.items():
        spark.udf.register(name, f)
    spark.udtf.register("segments_of", SegmentsOf)
    # the pronunciation rules as SQL functions of one word
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION phone_key(word STRING) RETURNS STRING RETURN {_sql_key(ph)}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION phones(word STRING) RETURNS ARRAY<STRING> RETURN filter(split(phone_key(word), ''), c -> c <> '')")


def _sql_key(ph) -> str:
    x = f"translate(lower(word), '{ph.ACCENTS[0]}', '{ph.ACCENTS[1]}')"
    for a, b in ph.DIGRAPHS:
        x = f"replace({x}, '{a}', '{b}')"
    x = f"translate({x}, '{ph.MERGED[0]}', '{ph.MERGED[1]}')"
    for c in ph.SYMBOLS:
        x = f"regexp_replace({x}, '{c}+', '{c}')"
    return x


