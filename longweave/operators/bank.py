"""A bounded bank of the newest states: appended files, evicted by arrival.  Never a driver list."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def newest(states: DataFrame, cap: int, arrival: str = "arrival") -> DataFrame:
    """The cap newest states (arrival is a total order): a top-k, to which each task sends at most cap rows."""
    return states.orderBy(F.desc(arrival)).limit(cap)


class MemoryBank:
    """Append-only Parquet under path, one folder per iteration; push overwrites its own iteration, so it is idempotent.

    size: the column that says how many states a row holds; one each if None.  Rows of several states stay whole, so what
    is read may exceed cap by a part of the oldest iteration held.
    """

    def __init__(self, spark: SparkSession, path: str, cap: int = 100_000, size: str | None = None):
        self.spark, self.path, self.cap, self.size = spark, path, cap, size

    def push(self, states: DataFrame, iteration: int) -> None:
        states.write.mode("overwrite").parquet(f"{self.path}/iter={iteration}")

    def _iterations(self, rows: DataFrame) -> list[tuple[int, int, int]]:
        """(iteration, states, room left when its turn comes) from the newest to the oldest that has room."""
        n = F.sum(self.size) if self.size else F.count("*")
        held, room = [], self.cap
        for r in rows.groupBy("iter").agg(n.alias("n")).orderBy(F.desc("iter")).collect():
            if room <= 0:
                break
            held.append((r["iter"], r["n"], room))
            room -= r["n"]
        return held

    def _rows(self) -> DataFrame:
        return self.spark.read.option("basePath", self.path).parquet(f"{self.path}/iter=*")

    def evict(self) -> None:
        """Delete iterations that the cap no longer reaches."""
        oldest = min((i for i, _, _ in self._iterations(self._rows())), default=0)
        conf, jvm = self.spark._jsc.hadoopConfiguration(), self.spark._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        store = root.getFileSystem(conf)
        for f in store.listStatus(root):
            name = f.getPath().getName()
            if name.startswith("iter=") and int(name[5:]) < oldest:
                store.delete(f.getPath(), True)

    def read(self) -> DataFrame:
        """The newest cap states by (iteration, arrival)."""
        rows, out = self._rows(), None
        for it, n, room in self._iterations(rows):  # whole iterations as long as they fit, the newest part of the next
            part = rows.filter(F.col("iter") == it)
            if n > room and not self.size:
                part = newest(part, room)
            out = part if out is None else out.unionByName(part)
        return rows.limit(0) if out is None else out
