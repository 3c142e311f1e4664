"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``).

    Where it is unset, a local session (tests) gets a folder of its own; a cluster gets an error,
    as a machine-local folder would be wrong there.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    own = getattr(spark.sparkContext, "_own_shared_dir", None)
    if own is None:
        own = spark.sparkContext._own_shared_dir = "file://" + tempfile.mkdtemp(prefix="shared-")
    return own


def small_batches(spark: SparkSession, rows: int = 1000) -> SparkSession:
    """Arrow batches of at most so many rows: whole texts make large rows, and two copies of a batch are held."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
    return spark


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write once to the shared folder and read back: cuts the lineage and survives lost executors."""
    spark, path = df.sparkSession, new_path(df.sparkSession, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def id_crc(col: str) -> Column:
    return F.crc32(F.col(col).cast("string").cast("binary"))


def hash_share(col: str) -> Column:
    """A number in [0, 1) that depends on the id alone."""
    return F.pmod(F.xxhash64(F.col(col), F.lit("sample")), F.lit(1 << 20)) / F.lit(float(1 << 20))


def runs(texts: list, limit: int = 1 << 21) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts add up to about ``limit`` characters, at least one row each."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        n = len(t) + 1 if t else 1
        if size and size + n > limit:
            yield start, i
            start, size = i, 0
        size += n
    if start < len(texts):
        yield start, len(texts)


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list:
    """Texts of a batch; null becomes the empty text."""
    return [t or "" for t in batch.column(name).to_pylist()]


def free_name(name: str, columns: list[str]) -> str:
    """The name, lengthened until no column is called so in any case."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name
