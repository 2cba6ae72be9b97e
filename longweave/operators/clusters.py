"""Centroids, labels, ranks and blocks: the parts of the cluster-attention layer, in long form."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from longweave.functions import kernels
from longweave.functions.vectors import cosine, dot, l2_distance


def label_means(vectors: DataFrame, label: str = "label", vec: str = "embedding") -> DataFrame:
    """(cid, vec): coordinate-wise mean per label; partial sums only travel."""
    each = vectors.select(F.col(label).alias("cid"), F.posexplode(vec).alias("j", "v")).groupBy("cid", "j").agg(F.avg(F.col("v").cast("double")).alias("v"))
    return each.groupBy("cid").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "v"))), lambda s: s["v"]).alias("vec"))


def chain(centroids: DataFrame, ordered: bool = True) -> DataFrame:
    """(ord, cid, vec) by the greedy walk from the smallest cid.  Centroids are few by construction, so the driver walks."""
    rows = centroids.select("cid", "vec").orderBy("cid").collect()
    order = kernels.chain_order(np.array([r["vec"] for r in rows])) if ordered and rows else range(len(rows))
    return centroids.sparkSession.createDataFrame([(k, rows[i]["cid"], rows[i]["vec"]) for k, i in enumerate(order)], "ord int, cid int, vec array<double>")


def nearest(states: DataFrame, chained: DataFrame, metric: str = "cosine") -> DataFrame:
    """states with cluster, the ord of the nearest centroid (ties: the smaller), by built-in functions.

    The few centroids come along as one broadcast row.
    """
    near = {"cosine": cosine, "dot": dot, "l2": lambda a, b: -l2_distance(a, b)}[metric]
    table = chained.agg(F.array_sort(F.collect_list(F.struct(F.col("ord"), F.col("vec").alias("cvec")))).alias("_c"))
    best = F.array_max(F.transform("_c", lambda c: F.struct(near(F.col("vec"), c["cvec"]).alias("s"), (-c["ord"]).alias("o"))))
    return states.crossJoin(F.broadcast(table)).withColumn("cluster", (-best["o"]).cast("int")).drop("_c")


def nearest_fast(states: DataFrame, centroids: np.ndarray, metric: str = "cosine", vec: str = "vec") -> DataFrame:
    """The same by one matrix product per Arrow batch."""
    held, at = states.sparkSession.sparkContext.broadcast(centroids), states.columns.index(vec)
    from pyspark.sql.types import StructType

    def label(batches):
        for b in batches:
            v = np.array(b.column(at).to_pylist(), dtype=np.float64).reshape(b.num_rows, -1)
            got = kernels.assign(v, held.value, metric) if b.num_rows else np.empty(0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.int32())], [*b.schema.names, "cluster"])

    return states.mapInArrow(label, StructType([*states.schema.fields]).add("cluster", "integer"))


def cluster_rank(states: DataFrame) -> DataFrame:
    """srank: place in the order of (cluster, hpos) within the sequence."""
    return states.withColumn("srank", F.row_number().over(Window.partitionBy("seq_id").orderBy("cluster", "hpos")) - 1)


def cluster_rank_counting(states: DataFrame, span: int = 4096) -> DataFrame:
    """The same rank for sequences beyond one task: counts per (sequence, cluster) and per span of hpos within give each
    span's first rank; only spans are ordered within.  A window holds a sequence's clusters, or a cluster's spans."""
    cut = states.withColumn("_span", F.floor(F.col("hpos") / span))
    counts = cut.groupBy("seq_id", "cluster", "_span").agg(F.count("*").alias("_n"))
    earlier = Window.rowsBetween(Window.unboundedPreceding, -1)
    first = counts.groupBy("seq_id", "cluster").agg(F.sum("_n").alias("_n")).withColumn("_first", F.coalesce(F.sum("_n").over(earlier.partitionBy("seq_id").orderBy("cluster")), F.lit(0))).drop("_n")
    within = F.coalesce(F.sum("_n").over(earlier.partitionBy("seq_id", "cluster").orderBy("_span")), F.lit(0))
    before = counts.withColumn("_before", within).drop("_n").join(first, ["seq_id", "cluster"])
    local = F.row_number().over(Window.partitionBy("seq_id", "cluster", "_span").orderBy("hpos")) - 1
    placed = cut.withColumn("_local", local).join(before, ["seq_id", "cluster", "_span"])
    return placed.withColumn("srank", (F.col("_first") + F.col("_before") + F.col("_local")).cast("int")).drop("_span", "_local", "_before", "_first")


def chunk(ranked: DataFrame, stride: int, layout: str = "uniform") -> DataFrame:
    """block: uniform cuts of stride rows; strict ones start anew at each cluster; padded: the cluster itself."""
    if layout == "uniform":
        return ranked.withColumn("block", F.floor(F.col("srank") / stride).cast("int"))
    if layout == "padded":
        return ranked.withColumn("block", F.col("cluster"))
    within = F.row_number().over(Window.partitionBy("seq_id", "cluster").orderBy("hpos")) - 1
    return ranked.withColumn("block", F.col("cluster") * 1_000_000 + F.floor(within / stride).cast("int"))


def attend(blocks: DataFrame, keys: list[str], scale: float) -> DataFrame:
    """Softmax attention among the rows that share keys, by a join and sums (identity projections): adds out."""
    other = blocks.select(*keys, F.col("vec").alias("_kv"))
    pair = blocks.join(other, keys).withColumn("_e", F.exp(dot("vec", "_kv") * scale))
    each = pair.select("hpos", "seq_id", "_e", F.posexplode("_kv").alias("j", "v"))
    out = each.groupBy("seq_id", "hpos", "j").agg((F.sum(F.col("_e") * F.col("v")) / F.sum("_e")).alias("o"))
    return out.groupBy("seq_id", "hpos").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "o"))), lambda s: s["o"]).alias("out"))


def kmeans_step(bank: DataFrame, centroids: np.ndarray, vec: str = "vec") -> DataFrame:
    """(cid, n, vec) after one step; tasks send a row of sums for each centroid only."""
    held, at = bank.sparkSession.sparkContext.broadcast(centroids), bank.columns.index(vec)

    def partial(batches):
        total, n = np.zeros_like(held.value), np.zeros(len(held.value), np.int64)
        for b in batches:
            v = np.array(b.column(at).to_pylist(), dtype=np.float64).reshape(b.num_rows, -1)
            if len(v):
                label = kernels.assign(v, held.value, "l2")
                np.add.at(total, label, v)
                n += np.bincount(label, minlength=len(n))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(n)), pa.int32()), pa.array(n), pa.array(list(total), pa.list_(pa.float64()))], ["cid", "n", "s"])

    sums = bank.mapInArrow(partial, "cid int, n long, s array<double>")
    each = sums.select("cid", "n", F.posexplode("s").alias("j", "v")).groupBy("cid", "j").agg(F.sum("n").alias("n"), F.sum("v").alias("v"))
    return each.groupBy("cid").agg(F.first("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("j", (F.col("v") / F.greatest("n", F.lit(1))).alias("v")))), lambda s: s["v"]).alias("vec"))


def kmeans(bank: DataFrame, init: np.ndarray, iters: int = 10, tol: float = 1e-9, vec: str = "vec") -> np.ndarray:
    """Lloyd over a distributed bank: each pass is a broadcast, a narrow map and one small sum; empty clusters stay."""
    c = np.array(init, dtype=np.float64)
    for _ in range(iters):
        new = c.copy()
        for r in kmeans_step(bank, c, vec).collect():  # one row per centroid
            if r["n"]:
                new[r["cid"]] = r["vec"]
        moved, c = np.abs(new - c).max(), new
        if moved <= tol:
            break
    return c


def mixture_sums(bank: DataFrame, weights: np.ndarray, means: np.ndarray, covs: np.ndarray, at: int) -> list:
    """Per component (n, sum, sum of outer products) under the given mixture; tasks send one row for each component only."""
    held = bank.sparkSession.sparkContext.broadcast((weights, means, covs))
    k, d = means.shape

    def partial(batches):
        n, s, ss = np.zeros(k), np.zeros((k, d)), np.zeros((k, d, d))
        for b in batches:
            x = np.array(b.column(at).to_pylist(), dtype=np.float64).reshape(b.num_rows, d)
            r = kernels.responsibilities(x, *held.value)
            n += r.sum(0)
            s += r.T @ x
            for c in range(k):
                ss[c] += (x * r[:, c : c + 1]).T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(k), pa.int32()), pa.array(n), pa.array(list(s), pa.list_(pa.float64())), pa.array(list(ss.reshape(k, -1)), pa.list_(pa.float64()))], ["cid", "n", "s", "ss"])

    add = lambda c: F.aggregate(F.collect_list(c), F.array_repeat(F.lit(0.0), d if c == "s" else d * d), lambda a, x: F.zip_with(a, x, lambda u, v: u + v)).alias(c)
    sums = bank.mapInArrow(partial, "cid int, n double, s array<double>, ss array<double>")
    return sums.groupBy("cid").agg(F.sum("n").alias("n"), add("s"), add("ss")).orderBy("cid").collect()


def mixture(bank: DataFrame, init: np.ndarray, iters: int = 5, ridge: float = 1e-3, vec: str = "vec") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(weights, means, covariances) of a mixture of normal distributions by expectation and maximisation from means init.

    Densities stay logarithms and covariances get a ridge (a share of the mean variance), so a component of few or equal vectors is
    no singular one; one that loses all its weight keeps its place.
    """
    k, d = init.shape
    at = bank.columns.index(vec)
    weights, means, covs = np.full(k, 1 / k), np.array(init, dtype=np.float64), np.repeat(np.eye(d)[None], k, 0)
    one = mixture_sums(bank, np.ones(1), means[:1], covs[:1], at)[0]
    if not one["n"]:
        return weights, means, covs
    spread = (np.array(one["ss"]).reshape(d, d).trace() - np.square(one["s"]).sum() / one["n"]) / one["n"] / d
    spread = max(spread, 1e-12)
    covs = covs * spread
    for _ in range(iters):
        rows = mixture_sums(bank, weights, means, covs, at)
        n = np.array([r["n"] for r in rows])
        weights = n / n.sum()
        for c in np.flatnonzero(n > 1e-9):
            means[c] = np.array(rows[c]["s"]) / n[c]
            covs[c] = np.array(rows[c]["ss"]).reshape(d, d) / n[c] - np.outer(means[c], means[c]) + ridge * spread * np.eye(d)
    return weights, means, covs


def likeliest(bank: DataFrame, fitted: tuple, vec: str = "vec") -> DataFrame:
    """(prediction, vec): the component of each vector."""
    held, at = bank.sparkSession.sparkContext.broadcast(fitted), bank.columns.index(vec)

    def label(batches):
        for b in batches:
            x = np.array(b.column(at).to_pylist(), dtype=np.float64).reshape(b.num_rows, held.value[1].shape[1])
            yield pa.RecordBatch.from_arrays([pa.array(kernels.responsibilities(x, *held.value).argmax(1), pa.int32()), b.column(at)], ["prediction", "vec"])

    return bank.mapInArrow(label, "prediction int, vec array<double>")
