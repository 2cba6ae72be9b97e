"""Nearest neighbours by inner product: one hierarchical navigable small-world graph per shard, results merged.

Equal vectors are one node, with the TOP + 1 smallest vec_ids that carry it; nodes are dealt to shards of about SHARD rows
by hash.  A shard's graph is built and searched for many points at a time (numpy).  Level l holds the first
n / DEGREE**l nodes of the shard's order, so each level is a prefix; links are flat arrays, one row of -1 padded places per
node.  A last coordinate makes all norms equal, so the nearest by distance are the largest inner products.
Scores are inner products of the given vectors in double precision.  Vectors that are null, zero, of another length than
most, or hold nulls or non-finite components take no part, nor rows without vec_id; a repeated vec_id with the same vector
counts once; as a query, a vec_id with several vectors stands for the smallest of them.  With fewer candidates than asked, all come.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from longweave.llm.common import column, cut, table

TOP, SHARD, DEGREE, BUILD_EF, SEARCH_EF, EXPAND = 20, 16_384, 16, 64, 200, 4


def links_at(level: int, degree: int = DEGREE) -> int:
    return degree if level else 2 * degree


def beam(x: np.ndarray, links: np.ndarray, q: np.ndarray, entry: np.ndarray, ef: int) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, similarities), best first, of an ef-wide search for each row of q; -1 pads."""
    b, row = len(q), np.arange(len(q))[:, None]
    seen = np.zeros((b, len(links) + 1), dtype=bool)  # the last column takes the padding
    node = np.full((b, ef), -1, dtype=np.int64)
    sim = np.full((b, ef), -np.inf, dtype=np.float32)
    done = np.ones((b, ef), dtype=bool)
    entry = np.sort(entry.reshape(b, -1)[:, :ef], 1)
    entry[:, 1:][entry[:, 1:] == entry[:, :-1]] = -1
    node[:, : entry.shape[1]] = entry
    sim[:, : entry.shape[1]] = np.where(entry >= 0, np.einsum("bkd,bd->bk", x[entry], q), -np.inf)
    done[:, : entry.shape[1]] = entry < 0
    seen[row, entry] = True
    live = np.arange(b)
    while len(live):
        open_ = np.where(done[live], -np.inf, sim[live])
        at = np.argpartition(-open_, min(EXPAND, ef) - 1, 1)[:, :EXPAND]
        r = np.arange(len(live))[:, None]
        some = open_[r, at] > -np.inf
        busy = some.any(1)
        live, at, some, r = live[busy], at[busy], some[busy], np.arange(busy.sum())[:, None]
        if not len(live):
            break
        done[live[:, None], at] = True
        from_ = np.where(some, node[live[:, None], at], -1)
        new = np.where(from_[:, :, None] >= 0, links[from_], -1).reshape(len(live), -1)
        new = np.where(seen[live[:, None], new], -1, new)
        new.sort(1)
        new[:, 1:][new[:, 1:] == new[:, :-1]] = -1
        new = new[:, (new >= 0).any(0)]
        if not new.shape[1]:
            continue
        seen[live[:, None], new] = True
        s = np.where(new >= 0, np.einsum("bkd,bd->bk", x[new], q[live]), -np.inf)
        all_s, all_n = np.concatenate([sim[live], s], 1), np.concatenate([node[live], new], 1)
        all_d = np.concatenate([done[live], new < 0], 1)
        keep = np.argpartition(-all_s, ef - 1, 1)[:, :ef]
        sim[live], node[live], done[live] = all_s[r, keep], all_n[r, keep], all_d[r, keep]
    order = np.argsort(-sim, 1, kind="stable")
    return node[row, order], sim[row, order]


def diverse(x: np.ndarray, node: np.ndarray, sim: np.ndarray, most: int) -> np.ndarray:
    """Of candidates, best first, those nearer to the row's point than to any one chosen; the nearest others fill up."""
    b, w = node.shape
    ok = node >= 0
    between = np.einsum("bid,bjd->bij", x[node], x[node])
    chosen = np.zeros((b, w), dtype=bool)
    closest = np.full((b, w), -np.inf, dtype=np.float32)
    n = np.zeros(b, dtype=np.int64)
    for j in range(w):
        take = ok[:, j] & (sim[:, j] > closest[:, j]) & (n < most)
        chosen[:, j] = take
        n += take
        closest = np.where(take[:, None], np.maximum(closest, between[:, j]), closest)
    rank = np.where(chosen, 0, np.where(ok, 1, 2)) * w + np.arange(w)
    order = np.argsort(rank, 1, kind="stable")[:, :most]
    out = np.where(np.take_along_axis(ok, order, 1), np.take_along_axis(node, order, 1), -1)
    return np.pad(out, ((0, 0), (0, most - out.shape[1])), constant_values=-1)


class Graph:
    def __init__(self, x: np.ndarray, levels: list[np.ndarray]):
        self.x, self.levels = x, levels

    @classmethod
    def build(cls, x: np.ndarray, degree: int = DEGREE, ef: int = BUILD_EF) -> Graph:
        sizes = [len(x)]
        while sizes[-1] > 4 * degree:
            sizes.append(sizes[-1] // degree)
        graph = cls(x, [])
        for level in range(len(sizes) - 1, -1, -1):
            graph.levels.insert(0, cls._layer(graph, x[: sizes[level]], links_at(level, degree), ef))
        return graph

    @staticmethod
    def _layer(above: Graph, x: np.ndarray, most: int, ef: int) -> np.ndarray:
        links = np.full((len(x), most), -1, dtype=np.int64)
        at = min(len(x), 2 * most)
        own = x[:at] @ x[:at].T
        np.fill_diagonal(own, -np.inf)
        order = np.argsort(-own, 1, kind="stable")[:, : at - 1]
        if at > 1:
            links[:at] = diverse(x, order, np.take_along_axis(own, order, 1), most)
        while at < len(x):
            n = min(512, at, len(x) - at)
            q = x[at : at + n]
            entry = above.entries(q)
            node, sim = beam(x, links[:at], q, np.where(entry < at, entry, 0), ef)
            picked = diverse(x, node, sim, max(most // 2, 4))
            links[at : at + n, : picked.shape[1]] = picked
            to, frm = picked.ravel(), np.repeat(np.arange(at, at + n), picked.shape[1])
            to, frm = to[to >= 0], frm[to >= 0]
            order = np.argsort(to, kind="stable")
            to, frm = to[order], frm[order]
            hit, first, count = np.unique(to, return_index=True, return_counts=True)
            wide = np.full((len(hit), most + count.max()), -1, dtype=np.int64)
            wide[:, :most] = links[hit]
            wide[np.repeat(np.arange(len(hit)), count), most + np.arange(len(to)) - np.repeat(first, count)] = frm
            s = np.where(wide >= 0, np.einsum("bkd,bd->bk", x[wide], x[hit]), -np.inf)
            order = np.argsort(-s, 1, kind="stable")[:, : max(2 * most, most + 8)]
            links[hit] = diverse(x, np.take_along_axis(wide, order, 1), np.take_along_axis(s, order, 1), most)
            at += n
        return links

    def entries(self, q: np.ndarray) -> np.ndarray:
        """Where to enter the level below those there are."""
        at = np.zeros((len(q), 1), dtype=np.int64)
        for links in reversed(self.levels):
            at = beam(self.x, links, q, at, EXPAND)[0]
        return at

    def search(self, q: np.ndarray, ef: int = SEARCH_EF) -> np.ndarray:
        at = np.zeros((len(q), 1), dtype=np.int64)
        for links in reversed(self.levels[1:]):
            at = beam(self.x, links, q, at, EXPAND)[0]
        return beam(self.x, self.levels[0], q, at, max(ef, EXPAND))[0]


def _usable(vectors: DataFrame, vector: str) -> DataFrame:
    own = vectors.select(column(vectors, "vec_id", "long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v")).filter("vec_id is not null and v is not null and size(v) > 0")
    own = own.filter("forall(v, e -> e is not null and not isnan(e) and abs(e) < double('infinity')) and exists(v, e -> e <> 0)")
    widths = own.groupBy(F.size("v").alias("w")).agg(F.count("*").alias("c")).orderBy(F.desc("c"), "w").limit(1).collect()
    return own.filter(F.size("v") == (widths[0]["w"] if widths else 1))


def build_index(vectors: DataFrame, vector: str = "embedding", shard_rows: int = SHARD, top: int = TOP) -> tuple[DataFrame, int]:
    """(index, shards): rows shard, node, v, ids and, per level, the node's flat links."""
    own = _usable(vectors, vector)
    few = Window.partitionBy("v").orderBy("vec_id")  # copies beyond the rank that any answer can hold need no place
    nodes = cut(own.distinct().withColumn("r", F.row_number().over(few)).filter(F.col("r") <= top + 1).groupBy("v").agg(F.array_sort(F.collect_list("vec_id")).alias("ids")))
    size = nodes.agg(F.count("*"), F.max(F.expr("aggregate(v, 0d, (a, e) -> a + e * e)"))).first()
    shards, longest = max(1, -(-size[0] // shard_rows)), float(size[1] or 1.0)

    def build(key, t):
        ids = t["ids"].to_pylist()
        v = np.array(t["v"].to_pylist(), dtype=np.float64)
        order = np.random.default_rng(1).permutation(np.argsort([i[0] for i in ids], kind="stable"))
        v = v[order]
        x = np.concatenate([v, np.sqrt(np.maximum(0, longest - (v * v).sum(1)))[:, None]], 1) / np.sqrt(longest)
        graph = Graph.build(x.astype(np.float32))
        links = [[a[i].astype(np.int32) for a in graph.levels if i < len(a)] for i in range(len(v))]
        flat = [np.concatenate(k) for k in links]
        return pa.table({"shard": pa.array([key[0].as_py()] * len(v), pa.int32()), "node": pa.array(np.arange(len(v)), pa.int32()), "v": pa.array(list(v), pa.list_(pa.float64())), "ids": pa.array([ids[i] for i in order], pa.list_(pa.int64())), "links": pa.array(flat, pa.list_(pa.int32()))})

    dealt = nodes.withColumn("shard", F.pmod(F.xxhash64(F.col("ids")[0]), F.lit(shards)).cast("int"))
    return cut(dealt.groupBy("shard").applyInArrow(build, "shard int, node int, v array<double>, ids array<long>, links array<int>")), shards


def _load(rows: list[tuple], longest: float) -> tuple[Graph, np.ndarray, list[list[int]]]:
    """(graph, vectors, ids) of a shard's rows (node, v, ids, links), in the order of node."""
    v = np.array([r[1] for r in rows], dtype=np.float64)
    flat = [np.array(r[3], dtype=np.int64) for r in rows]
    levels, at = [], 0
    while True:
        width = links_at(len(levels))
        own = [f[at : at + width] for f in flat if len(f) > at]
        if not own:
            break
        levels.append(np.stack(own))
        at += width
    x = np.concatenate([v, np.sqrt(np.maximum(0, longest - (v * v).sum(1)))[:, None]], 1) / np.sqrt(longest)
    return Graph(x.astype(np.float32), levels), v, [r[2] for r in rows]


def search(index: DataFrame, shards: int, queries: DataFrame, top: int = TOP, ef: int = SEARCH_EF) -> DataFrame:
    """queries (query_id, v) against the index: query_id, rank, vec_id, score.

    A shard's rows come to its task once, before the queries, which stream past it batch by batch.
    """
    longest = float(index.agg(F.max(F.expr("aggregate(v, 0d, (a, e) -> a + e * e)"))).first()[0] or 1.0)
    nodes = index.select("shard", F.lit(0).alias("kind"), F.col("node").cast("long").alias("id"), "v", "ids", "links")
    asked = queries.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.lit(1).alias("kind"), F.col("query_id").alias("id"), "v", F.lit(None).cast("array<long>").alias("ids"), F.lit(None).cast("array<int>").alias("links"))
    dealt = nodes.unionByName(asked).repartition(max(shards, 1), "shard").sortWithinPartitions("shard", "kind", "id")

    def answers(graph: Graph, v: np.ndarray, ids: list, names: list, q: np.ndarray) -> pa.RecordBatch:
        out: tuple[list, list, list] = ([], [], [])
        for at in range(0, len(q), 512):
            part = q[at : at + 512]
            near = graph.search(np.concatenate([part, np.zeros((len(part), 1))], 1).astype(np.float32), ef)
            exact = np.where(near >= 0, np.einsum("bkd,bd->bk", v[near], part), -np.inf)
            for k, order in enumerate(np.argsort(-exact, 1, kind="stable")[:, : 2 * top]):
                name = names[at + k]
                got = [(-s, i) for s, j in zip(exact[k, order].tolist(), near[k, order].tolist(), strict=True) if j >= 0 for i in ids[j] if i != name]
                for s, i in sorted(got)[:top]:
                    out[0].append(name), out[1].append(i), out[2].append(-s)
        return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["query_id", "vec_id", "score"])

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, loaded = None, [], None
        for batch in batches:
            shard, kind = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            cuts = np.flatnonzero((shard[1:] != shard[:-1]) | (kind[1:] != kind[:-1])) + 1
            for a, z in zip([0, *cuts], [*cuts, len(shard)], strict=True):
                if z <= a:
                    continue
                part = batch.slice(a, z - a)
                if shard[a] != now:
                    now, held, loaded = shard[a], [], None
                if kind[a] == 0:
                    held += zip(*(part.column(k).to_pylist() for k in (2, 3, 4, 5)), strict=True)
                elif held:
                    loaded = loaded or _load(held, longest)
                    yield answers(*loaded, part.column(2).to_pylist(), np.array(part.column(3).to_pylist(), dtype=np.float64))

    found = dealt.mapInArrow(find, "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")


def op3_hnsw(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    index, shards = build_index(vectors)
    asked = _usable(vectors, "embedding").filter("vec_id % 20 = 0").groupBy(F.col("vec_id").alias("query_id")).agg(F.min("v").alias("v"))
    return search(index, shards, asked)
