"""Overlapping windows in long form (one row per state) and the packed form that kernels read."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from longweave.functions.kernels import check_window


@dataclass(frozen=True)
class WindowSpec:
    win: int = 256
    stride: int = 224
    q_len: int = 0

    def __post_init__(self):
        check_window(self.win, self.stride)


def slice_windows(states: DataFrame, spec: WindowSpec) -> DataFrame:
    """Each context row once per window that holds it: adds win and row (question rows come first).  No shuffle."""
    first = F.greatest(F.lit(0), F.ceil((F.col("pos") - spec.win + 1) / spec.stride)).cast("int")
    out = states.withColumn("win", F.explode(F.sequence(first, F.floor(F.col("pos") / spec.stride).cast("int"))))
    return out.withColumn("row", F.col("pos") - F.col("win") * spec.stride + spec.q_len)


def bounds(lengths: DataFrame, spec: WindowSpec, key: str = "seq_id", length: str = "x") -> DataFrame:
    """(key, win, lo, hi) of every window of sequences of the given lengths; the last ones are ragged."""
    k = F.explode(F.sequence(F.lit(0), F.ceil(F.col(length) / spec.stride).cast("int") - 1)).alias("win")
    out = lengths.filter(F.col(length) > 0).select(key, length, k)
    return out.select(key, "win", (F.col("win") * spec.stride).cast("int").alias("lo"), F.least(F.col(length), F.col("win") * spec.stride + spec.win).cast("int").alias("hi"))


def with_question(windows: DataFrame, question: DataFrame, spec: WindowSpec) -> DataFrame:
    """Rows (seq_id, win, row, kind, tok) with every question row in front of every window of its sequence."""
    context = windows.select("seq_id", "win", "row", F.lit("c").alias("kind"), "tok")
    wins = windows.select("seq_id", "win").distinct()
    return context.unionByName(wins.join(question, "seq_id").select("seq_id", "win", F.col("qpos").alias("row"), F.lit("q").alias("kind"), "tok"))


def merge_overlaps(windows: DataFrame, spec: WindowSpec, rule: str = "cover_mean") -> DataFrame:
    """Coordinate-wise mean of a context row over all windows that hold it, read from the values before merging.

    pair_mean is the same for windows of at most two strides and refuses others.
    """
    if rule == "pair_mean" and spec.win > 2 * spec.stride:
        raise ValueError("more than two windows may hold one row")
    each = windows.select("*", F.posexplode("vec").alias("j", "v")).withColumn("v", F.avg("v").over(Window.partitionBy("seq_id", "pos", "j")))
    keys = [c for c in windows.columns if c != "vec"]
    return each.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("vec"))


def dedup_concat(windows: DataFrame, spec: WindowSpec) -> DataFrame:
    """The first question and stride rows of each window; hpos counts them within the sequence."""
    step = spec.q_len + spec.stride
    return windows.filter(F.col("row") < step).withColumn("hpos", F.col("win") * step + F.col("row"))


def rewindow(states: DataFrame, spec: WindowSpec) -> DataFrame:
    """Windows again from de-duplicated context states."""
    step = spec.q_len + spec.stride
    pos = states.withColumn("pos", F.col("win") * spec.stride + F.col("row") - spec.q_len).filter(F.col("row") >= spec.q_len)
    return slice_windows(pos.drop("win", "row", "hpos"), spec) if step else pos


def pack(windows: DataFrame) -> DataFrame:
    """One row per window: (seq_id, win, n_rows, flat)."""
    rows = F.array_sort(F.collect_list(F.struct("row", "vec")))
    return windows.groupBy("seq_id", "win").agg(F.count("*").cast("int").alias("n_rows"), F.flatten(F.transform(rows, lambda r: r["vec"])).alias("flat"))


def unpack(packed: DataFrame, d: int) -> DataFrame:
    return packed.select("seq_id", "win", F.posexplode(F.transform(F.sequence(F.lit(0), F.col("n_rows") - 1), lambda i: F.slice("flat", i * d + 1, d))).alias("row", "vec"))
