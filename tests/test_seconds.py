"""Time ranges count seconds as the SQL twin does."""

from __future__ import annotations

import duckdb
from pyspark.sql import functions as F

import __spark_entry__ as entry


def test_times_count_as_the_nearest_second(spark, tmp_path):
    rows = [(i, 1, f"2024-01-01 {x}") for i, x in enumerate(("00:00:00.6", "00:59:59.9", "01:00:00.4", "01:00:00.5", "01:00:01.5", "01:00:02.4"))]
    df = spark.createDataFrame(rows, "event_id long, user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    df.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    mine = sorted(map(tuple, entry.queries()["win_range"](spark, str(tmp_path)).collect()))
    assert mine == sorted(con.execute(entry.oracle_sql()["win_range"]).fetchall())
