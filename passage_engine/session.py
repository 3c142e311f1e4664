"""Sessions: the library's code reaches the Python workers."""

from __future__ import annotations

import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> SparkSession:
    """Send this package to the executors, once for each Spark context.

    Needed where the workers' path lacks the package (it was neither installed nor given as --py-files).
    """
    context = spark.sparkContext
    if not getattr(context, "_passage_engine_sent", False):
        package = Path(__file__).parent
        zipped = shutil.make_archive(f"{tempfile.mkdtemp()}/passage_engine", "zip", package.parent, package.name)
        context.addPyFile(zipped)
        context._passage_engine_sent = True
    return spark


@contextmanager
def setting(spark: SparkSession, name: str, value: str) -> Iterator[SparkSession]:
    """The session with another value of a runtime setting, put back at the end."""
    before = spark.conf.get(name, None)
    spark.conf.set(name, value)
    try:
        yield spark
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def shared_base(spark: SparkSession) -> str:
    """The folder that the cluster shares (spark.checkpoint.dir).

    Where it is unset, a local session gets a temporary folder of its own; a cluster gets an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    own = getattr(spark.sparkContext, "_passage_engine_base", None)
    if own is None:
        own = spark.sparkContext._passage_engine_base = "file://" + tempfile.mkdtemp(prefix="shared-")
    return own


def own_folder(spark: SparkSession, base: str | None = None) -> str:
    """A new folder's name below ``base``, or else below the shared folder."""
    return f"{(base or shared_base(spark)).rstrip('/')}/{uuid.uuid4().hex}"
