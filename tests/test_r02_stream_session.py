"""Second review, F1: the result of a complete stream."""

import duckdb
from pyspark.sql import functions as F

from longweave.plans import registry

registry.everything()


def put(df, folder, name):
    df.coalesce(1).write.mode("overwrite").parquet(f"{folder}/{name}.parquet")


def test_session_results_are_files_and_late_files_count(spark, sf, tmp_path):
    """A second file with earlier times; the result doesn't pass through the driver's memory."""
    e = spark.read.parquet(f"{sf}/events.parquet")
    put(e, tmp_path, "events")
    e.withColumn("ts", F.expr("ts - interval 400 days")).withColumn("user_id", F.col("user_id") + 10**6).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    put(spark.read.parquet(f"{sf}/nation.parquet"), tmp_path, "nation")
    got = registry.QUERIES["stream_session"](spark, str(tmp_path))
    assert got.inputFiles()
    c = duckdb.connect()
    c.sql(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    assert sorted(map(tuple, got.collect())) == sorted(c.sql(registry.ORACLES["stream_session"]).fetchall())
