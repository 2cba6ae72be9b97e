"""Files around the engine: scratch folders in shared storage, other formats, partitioned and bucketed copies, streams."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, what: str) -> str:
    """A new path that all executors see: below spark.checkpoint.dir, else (local runs) a temporary folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
    base = base or "file://" + tempfile.mkdtemp(prefix="longweave-")
    return f"{base}/{what}-{uuid.uuid4().hex}"


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    path = scratch(df.sparkSession, fmt)
    df.write.format(fmt).option("header", True).save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).option("header", True).load(path)


def bucketed(df: DataFrame, name: str, key: str, n: int) -> DataFrame:
    """A table bucketed and sorted by key: later joins and groups on key need no shuffle."""
    df.write.mode("overwrite").bucketBy(n, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)


def stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A Parquet folder (or a file's folder) as a stream; NTZ times become timestamps, as watermarks need."""
    schema = spark.read.parquet(path).schema
    folder, _, name = path.rstrip("/").rpartition("/")
    read = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch)
    df = read.option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") and not _is_dir(spark, path) else read.parquet(path)
    for c, t in df.dtypes:
        if t == "timestamp_ntz":
            df = df.withColumn(c, df[c].cast("timestamp"))
    return df


def _is_dir(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()
