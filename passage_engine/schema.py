"""Schemas of the engine's tables, declared and never inferred."""

from __future__ import annotations

from pyspark.sql import types as T

SENTENCE = T.StructType([T.StructField("idx", T.IntegerType()), T.StructField("text", T.StringType()), T.StructField("n_tok", T.IntegerType()), T.StructField("ends_para", T.BooleanType())])
CORPUS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("corpus", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("split", T.StringType()), T.StructField("group_id", T.LongType()), T.StructField("n_sent", T.IntegerType()), T.StructField("sents", T.ArrayType(SENTENCE))])
WINDOW = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("win_no", T.IntegerType()), T.StructField("first", T.IntegerType()), T.StructField("last", T.IntegerType()), T.StructField("n_tok", T.IntegerType())])
PREDICTION = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("idx", T.IntegerType()), T.StructField("prob", T.DoubleType()), T.StructField("is_boundary", T.BooleanType()), T.StructField("win_no", T.IntegerType()), T.StructField("n_seen", T.IntegerType())])
SEGMENT = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("seg_no", T.IntegerType()), T.StructField("first", T.IntegerType()), T.StructField("last", T.IntegerType()), T.StructField("text", T.StringType())])
VOTE = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("idx", T.IntegerType()), T.StructField("annotator", T.IntegerType()), T.StructField("vote", T.IntegerType())])
LEXICON = T.StructType([T.StructField("word", T.StringType()), T.StructField("rank", T.IntegerType()), T.StructField("phones", T.ArrayType(T.StringType())), T.StructField("phone_key", T.StringType())])
RETURN = T.StructType([T.StructField("job_id", T.LongType()), T.StructField("doc_id", T.LongType()), T.StructField("model", T.StringType()), T.StructField("worker_id", T.LongType()), T.StructField("question", T.StringType()), T.StructField("correct", T.IntegerType()), T.StructField("minutes", T.DoubleType())])
EVENT = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def verify(df, schema: T.StructType):
    """Fail on reading if a column is missing or has another type; extra columns are allowed."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name] != f.dataType:
            raise ValueError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df
