"""Sources and sinks around the methods."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


def read_parquet(spark: SparkSession, path: str, columns: list[str], where: str | None = None) -> DataFrame:
    """Only the named columns; the filter reaches the scan."""
    df = spark.read.parquet(path)
    return (df.where(where) if where else df).select(*columns)


def read_json(spark: SparkSession, path: str, schema: str, corrupt: str = "_corrupt") -> DataFrame:
    """JSON lines with a declared schema; malformed lines keep their text in the named column."""
    return spark.read.schema(f"{schema}, {corrupt} string").option("columnNameOfCorruptRecord", corrupt).json(path)


def read_csv(spark: SparkSession, path: str, schema: str, corrupt: str = "_corrupt") -> DataFrame:
    return spark.read.schema(f"{schema}, {corrupt} string").option("header", True).option("columnNameOfCorruptRecord", corrupt).csv(path)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    """One row a file: (path, text)."""
    return spark.read.option("wholetext", True).text(path).select(F.input_file_name().alias("path"), F.col("value").alias("text"))


def write_partitioned(df: DataFrame, path: str, *by: str, rows_a_file: int = 1_000_000) -> None:
    """Parquet by corpus, language, split or the like; rebalanced first, so that a hot value makes several files and small ones few."""
    df.hint("rebalance", *by).write.mode("overwrite").option("maxRecordsPerFile", rows_a_file).partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "doc_id") -> None:
    """Table whose joins on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def unfinished(todo: DataFrame, done: DataFrame, key: str = "doc_id") -> DataFrame:
    """Rows whose results aren't there yet: what a resumed job has to do."""
    return todo.join(done.select(key).distinct(), key, "left_anti")


def save_checkpoint(spark: SparkSession, blob: bytes, path: str, name: str) -> None:
    """Model weights as a one-row Parquet."""
    spark.createDataFrame([(name, bytearray(blob))], "name string, weights binary").write.mode("overwrite").parquet(path)


def load_checkpoint(spark: SparkSession, path: str) -> bytes:
    return bytes(spark.read.parquet(path).select("weights").first()[0])


TRANSCRIPT = "key long, turn int, text string"


def transcript_rows(lines: Iterable[str | None]) -> Iterator[tuple]:
    """'key|turn|text' lines to rows; lines of fewer parts go, further bars belong to the text."""
    for line in lines:
        if line is not None and line.count("|") >= 2:
            key, turn, text = line.split("|", 2)
            yield int(key), int(turn), text


def read_transcript(lines: DataFrame, line: str = "line") -> DataFrame:
    """The same for lines that stand in a table: each task reads its own."""

    def run(frames):
        for pdf in frames:
            yield pd.DataFrame(list(transcript_rows(pdf[line])), columns=["key", "turn", "text"])

    return lines.select(line).mapInPandas(run, TRANSCRIPT)


class TranscriptSource(DataSource):
    """Transcripts given as option ``lines``: 'key|turn|text' lines; option ``partitions`` splits them."""

    @classmethod
    def name(cls) -> str:
        return "transcript"

    def schema(self) -> str:
        return TRANSCRIPT

    def reader(self, schema: StructType) -> DataSourceReader:
        return TranscriptReader(self.options)


class TranscriptReader(DataSourceReader):
    def __init__(self, options):
        self.lines = options.get("lines", "").split("\n")
        self.parts = int(options.get("partitions", "1"))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from transcript_rows(self.lines[partition.value :: self.parts])
