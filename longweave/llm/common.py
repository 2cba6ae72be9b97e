"""What the training-data operators share: lineage cuts, input preparation, fixed-size filters."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import tempfile
import zipfile
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PACKAGE = Path(__file__).resolve().parents[1]
_shipped: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see (spark.checkpoint.dir); set only where the session has none, as in tests."""
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not path:
        if not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors see")
        path = "file://" + tempfile.mkdtemp(prefix="longweave-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(path)
    return path


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and go on from there; a lost executor then costs no recomputation.

    The shuffle files behind it are of no more use; Spark deletes them once the driver has collected their handles.
    """
    shared_dir(df.sparkSession)
    out = df.checkpoint(eager=True)
    give_back()
    df.sparkSession.sparkContext._jvm.System.gc()
    return out


def give_back() -> None:
    """Return freed memory of the driver's Python to the system; the allocators keep it else, beside all that follows."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # another C library
        ctypes.CDLL(None).malloc_trim(0)


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers that were started without it on their path."""
    root = str(PACKAGE.parent)
    sc = spark.sparkContext
    if root in os.environ.get("PYTHONPATH", "").split(":") or sc.applicationId in _shipped:
        return
    _shipped.add(sc.applicationId)
    target = Path(tempfile.mkdtemp(prefix="longweave-ship-")) / f"{PACKAGE.name}.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, p.relative_to(PACKAGE.parent))
    sc.addPyFile(str(target))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tasks(spark: SparkSession, least: int = 1) -> int:
    return max(least, int(spark.conf.get("spark.sql.shuffle.partitions")))


def column(df: DataFrame, name: str, kind: str) -> Column:
    """df's column cast to kind; a typed null where the table lacks it.  Every operator starts here, so it ships, too."""
    ship(df.sparkSession)
    return df[name].cast(kind) if name in df.columns else F.lit(None).cast(kind)


def hash_sample(df: DataFrame, key: Column, n: int) -> DataFrame:
    """About the n rows of smallest hash of key, at most n; all rows if there are no more than that.

    Rows over the hash that about 1.3 n rows lie under go first, so tasks don't each send n rows to the driver.
    """
    total = max(1, df.count())
    held = df.withColumn("__h", F.pmod(F.xxhash64(key), F.lit(1 << 40)))
    share = (1.3 * n + 100) / total
    if share < 1:
        held = held.filter(F.col("__h") < int(share * (1 << 40)))
    return held.orderBy("__h").limit(n).drop("__h")


# ---------------------------------------------------------------- a Bloom filter of bounded size
LEAST_BITS, MOST_BITS = 1 << 20, 1 << 28
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def bloom(keys: DataFrame):
    """Broadcast bit array for keys (h1, h2), two hashes of each key: about 16 bits a key, at most MOST_BITS (32 MB).

    The bits are or-ed per 64-bit word in Spark, so at most bits / 64 rows reach the driver.  False positives only let
    more rows through (a few in a hundred, up to all if keys outnumber the bits); no key is lost.
    """
    bits = min(MOST_BITS, max(LEAST_BITS, 1 << (16 * keys.count()).bit_length()))
    at = keys.select(F.explode(F.array("h1", "h2")).alias("h")).select(F.pmod("h", F.lit(bits)).alias("at"))
    word = at.select(F.expr("cast(at div 64 as int)").alias("w"), F.expr("shiftleft(1L, cast(at % 64 as int))").alias("b"))
    rows = word.groupBy("w").agg(F.bit_or("b").alias("b")).toArrow()
    out = np.zeros(bits // 64, dtype=np.int64)
    out[rows["w"].to_numpy()] = rows["b"].to_numpy()
    return keys.sparkSession.sparkContext.broadcast(out.view(np.uint64))


def may_contain(words: np.ndarray, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
    """h1, h2: int64 hashes as given to bloom()."""
    bits = np.int64(len(words) * 64)
    got = None
    for h in (h1, h2):
        at = np.mod(h, bits).astype(np.uint64)
        hit = (words[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1)
        got = hit if got is None else got & hit
    return got.astype(bool)
