"""The refresh loop: a layer's centroids follow a bounded bank of the newest states of the layer below it.

A pass over the stream (sequences in the order of seq_id) is cut into iterations.  Each one pushes its states, evicts what
the cap no longer holds and, where due, fits K-Means to the bank from the centroids there are and renumbers them by the
greedy walk; what is labelled afterwards uses these.  Only states that the bank will hold are ever made.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.operators.bank import MemoryBank
from longweave.operators.fused import per_sequence
from longweave.session import persist_cut
from longweave.sources.tables import scratch

#: Ranges of seq_id that one count of lengths tells apart.
RANGES = 1024


@dataclass(frozen=True)
class Refresh:
    cap: int = 100_000
    iterations: int = 4  # of one pass
    every: int = 2  # iterations from refresh to refresh
    steps: int = 4  # of K-Means in each
    unit: bool = False  # fit unit vectors, as the cosine of the labels sees them
    fit: str = "lloyd"  # or bounded


@dataclass(frozen=True)
class Snapshot:
    epoch: int
    centroids: np.ndarray  # as K-Means numbers them
    moved: float  # mean distance from the snapshot before

    @property
    def ordered(self) -> np.ndarray:
        return self.centroids[K.chain_order(self.centroids)]


def newest_sequences(lengths: DataFrame, cap: int, lo: int, hi: int) -> int:
    """The largest seq_id in [lo, hi] from which on all sequences (seq_id, n) together hold cap states; lo if none does."""
    need = cap
    while hi > lo:
        width = max(1, -(-(hi - lo + 1) // RANGES))
        bucket = ((F.col("seq_id") - lo) / width).cast("long").alias("b")
        sizes = sorted(((r["b"], r["n"]) for r in lengths.filter(F.col("seq_id").between(lo, hi)).groupBy(bucket).agg(F.sum("n").alias("n")).collect()), reverse=True)
        for b, n in sizes:  # at most RANGES rows
            if n >= need:
                lo, hi = lo + b * width, min(hi, lo + (b + 1) * width - 1)
                break
            need -= n
        else:
            return lo
        if width == 1:
            return lo
    return lo


def fit(bank: DataFrame, init: np.ndarray, plan: Refresh) -> np.ndarray:
    """K-Means over a bank (seq_id, flat); it is bounded by its cap, so one task holds it.  len(init) rows come back."""
    d = init.shape[1]

    def run(batches):
        rows = [r for b in batches for r in zip(b.column(0).to_pylist(), (x.values.to_numpy() for x in b.column(1)), strict=True)]
        x = np.concatenate([np.empty(0), *(v for _, v in sorted(rows, key=lambda r: r[0]))]).reshape(-1, d)[-plan.cap :]
        if plan.unit:
            norm = np.linalg.norm(x, axis=1, keepdims=True)
            x = np.divide(x, norm, out=np.zeros_like(x), where=norm > 0)
        c = (K.kmeans_bounded if plan.fit == "bounded" else K.kmeans)(x, init, plan.steps)[0] if len(x) else init
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(c)), pa.int32()), pa.array(list(c), pa.list_(pa.float64()))], ["cid", "vec"])

    got = bank.select("seq_id", "flat").repartition(1).mapInArrow(run, "cid int, vec array<double>").orderBy("cid").collect()
    return np.array([r["vec"] for r in got])


def lengths_of(packed: DataFrame) -> DataFrame:
    """(seq_id, n): the tokens of each sequence."""
    return persist_cut(packed.select("seq_id", F.size("toks").alias("n")))


def between(packed: DataFrame) -> Callable[[int, int], DataFrame]:
    return lambda lo, hi: packed.filter(F.col("seq_id").between(lo, hi))


def refresh_loop(packed: DataFrame, encode: Callable[[list[str]], np.ndarray], init: np.ndarray, plan: Refresh = Refresh()) -> list[Snapshot]:  # noqa: B008
    """A snapshot for each refresh of one pass over packed (seq_id, toks).  encode: the states below the layer."""
    return refresh_loops(packed, encode, [init], plan)[0]


def refresh_loops(packed: DataFrame, encode: Callable[[list[str]], np.ndarray], inits: list[np.ndarray], plan: Refresh = Refresh(), within: Callable[[int, int], DataFrame] | None = None, lengths: DataFrame | None = None) -> list[list[Snapshot]]:  # noqa: B008
    """refresh_loop from each of inits, over one bank.  Texts are cut into tokens once for their lengths, and again only
    where the bank holds them.  within: packed between two seq_id, both included, where it can be had for less.  lengths:
    lengths_of(packed), where it is there already."""
    spark = packed.sparkSession
    lengths = lengths_of(packed) if lengths is None else lengths
    last = lengths.agg(F.max("seq_id")).first()[0]
    cs, out = list(inits), [[] for _ in inits]
    if last is None:
        return out
    bank = MemoryBank(spark, scratch(spark, "bank"), plan.cap, size="n")
    within = within or between(packed)

    def states(seq: int, toks: list[str]) -> list[dict]:
        return [{"seq_id": seq, "n": len(h), "flat": h.ravel()}] if len(h := encode(toks) if toks else np.empty((0, 1))) else []

    for i in range(1, plan.iterations + 1):
        lo, hi = (-(-(k * (last + 1)) // plan.iterations) for k in (i - 1, i))
        since = newest_sequences(lengths, plan.cap, lo, hi - 1)
        bank.push(per_sequence(within(since, hi - 1), states, "seq_id long, n long, flat array<double>"), i)
        bank.evict()
        for k, c in enumerate(cs) if i % plan.every == 0 else ():
            cs[k] = fit(bank.read(), c, plan)
            out[k].append(Snapshot(i // plan.every, cs[k], float(np.sqrt(((cs[k] - c) ** 2).sum(1)).mean())))
    return out


def snapshot_table(spark: SparkSession, layer: int, snapshots: list[Snapshot]) -> DataFrame:
    """(layer, epoch, ord, vec): what is kept of the fits, in chain order."""
    rows = [(layer, s.epoch, k, v.tolist()) for s in snapshots for k, v in enumerate(s.ordered)]
    return spark.createDataFrame(rows, "layer int, epoch int, ord int, vec array<double>")


def fit_stack(packed: DataFrame, plan, states_of: Callable[[list[str]], np.ndarray], how: Refresh = Refresh()):  # noqa: B008
    """plan with fitted centroids at its depths, from the lowest up: each bank holds the states right below its depth."""
    if plan.kind != "cluster":
        return plan
    for depth in plan.cal:
        below = plan
        got = refresh_loop(packed, lambda toks, p=below, k=depth: p.run(states_of(toks), below=k), plan.directions(depth), how)
        if got:
            plan = plan.with_centroids(depth, got[-1].ordered)
    return plan


def fit_stacks(packed: DataFrame, plans: list, states_of: Callable[[list[str]], np.ndarray], how: Refresh = Refresh(), within: Callable[[int, int], DataFrame] | None = None) -> list:  # noqa: B008
    """fit_stack of each plan.  Those that look further at one depth only, over the same layers, share their bank."""
    from longweave.plans.stack import common_depth

    out, groups = list(plans), []
    for k, plan in enumerate(plans):
        if plan.kind != "cluster" or len(plan.cal) != 1:
            out[k] = fit_stack(packed, plan, states_of, how)
            continue
        for own in groups:
            if plans[own[0]].cal == plan.cal and common_depth([plans[own[0]], plan]) == plan.cal[0]:
                own.append(k)
                break
        else:
            groups.append([k])
    lengths = None
    if len(groups) > 1:  # their banks hold the states of the same sequences, which are looked for and brought together once
        lengths, cut = lengths_of(packed), within or between(packed)
        within = cache(lambda lo, hi: persist_cut(cut(lo, hi)))
    for own in groups:
        first, depth = plans[own[0]], plans[own[0]].cal[0]
        got = refresh_loops(packed, lambda toks, p=first, n=depth: p.run(states_of(toks), below=n), [plans[k].directions(depth) for k in own], how, within, lengths)
        for k, snapshots in zip(own, got, strict=True):
            out[k] = plans[k].with_centroids(depth, snapshots[-1].ordered) if snapshots else plans[k]
    return out
