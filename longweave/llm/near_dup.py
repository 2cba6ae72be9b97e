"""Near-duplicate documents: fast similarity sketches, banding, exact verification, connected components.

A document is its set of distinct SHINGLE-word shingles (of all its words, if it has fewer; none without words).  Its
sketch has SIZE coordinates: in each round every element falls into a bin by hash, a bin keeps its first round's least
value, and after SIZE rounds bin j takes the least value of all elements, so every coordinate is filled.  Documents whose
sketches agree in all ROWS coordinates of one of BANDS bands are candidates; links are confirmed on the full sets.
At the threshold of 0.75 a pair shares no band with probability (1 - 0.75**5)**40 < 2e-5.

Groups of copies stay cheap: equal sets are one class at once; each band bucket first links its members to its least
document only; what then still lies in different components of a bucket is compared by sketch, linked by full sets.
Rows are documents of their own: null and empty texts are linked with nothing, a null doc_id neither (component null,
kept); rows that repeat a doc_id are judged by their own texts.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import bloom, column, cut, may_contain, table, tasks
from longweave.llm.graph import components
from longweave.llm.hashing import U, blocks, hashed, mix, ngrams

SHINGLE, PERCENT = 5, 75
SIZE, ROWS, BANDS = 200, 5, 40
#: Documents of a group in a block.
CELL = 512
#: A sketch of a pair at the threshold has a deviation of 0.031 at most; five of these below it is what is still verified.
NEAR = 0.59
_rng = np.random.Generator(np.random.PCG64(77))
SEEDS = _rng.integers(0, 2**64, 2 * SIZE, dtype=np.uint64)
WEIGHTS = _rng.integers(0, 2**63, ROWS, dtype=np.uint64) * U(2) + U(1)
EMPTY = U(2**64 - 1)


def shingle_sets(texts: list[str | None], n: int = SHINGLE) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    h, bound = hashed(texts)
    grams = ngrams(h, n)
    for a, z in zip(bound[:-1].tolist(), bound[1:].tolist(), strict=True):
        if z - a >= n:
            yield np.unique(grams[a : z - n + 1])
        elif z > a:
            yield mix(ngrams(h[a:z], z - a) + U(z - a))
        else:
            yield np.empty(0, np.uint64)


def sketch(s: np.ndarray) -> np.ndarray:
    """SIZE coordinates (round << 32 | value) of a set that isn't empty."""
    out = np.full(SIZE, EMPTY, dtype=np.uint64)
    done, step = 0, max(1, 1500 // len(s))
    while done < SIZE:
        rounds = np.arange(done, min(done + step, SIZE), dtype=np.uint64)
        h = mix(s[None, :] ^ SEEDS[done : done + len(rounds), None])
        at = ((h >> U(32)) * U(SIZE)) >> U(32)
        value = (rounds[:, None] << U(32)) | (h & U(0xFFFFFFFF))
        np.minimum.at(out, at.ravel().astype(np.int64), value.ravel())
        done += len(rounds)
        if out.max() != EMPTY:
            return out
    for j in np.flatnonzero(out == EMPTY):
        out[j] = U(int(j) + SIZE) << U(32) | (mix(s ^ SEEDS[SIZE + j]) & U(0xFFFFFFFF)).min()
    return out


def band_keys(coordinates: np.ndarray) -> np.ndarray:
    return mix((coordinates.reshape(BANDS, ROWS) * WEIGHTS).sum(1, dtype=np.uint64) ^ (np.arange(BANDS, dtype=np.uint64) * U(0x9E3779B97F4A7C15)))


def _signatures(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at, part in blocks(batch.column(1).to_pylist()):
            n, ka, kb, marks, bands = [], [], [], [], []
            for s in shingle_sets(part):
                n.append(len(s))
                if not len(s):
                    for x in (ka, kb, marks, bands):
                        x.append(None)
                    continue
                ka.append(int(mix(s).sum(dtype=np.uint64).astype(np.int64)))
                kb.append(int(np.bitwise_xor.reduce(mix(s + U(1))).astype(np.int64)))
                c = sketch(s)
                marks.append(mix(c).astype(np.uint16).tobytes())
                bands.append(band_keys(c).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(part)), pa.array(n, pa.int64()), pa.array(ka, pa.int64()), pa.array(kb, pa.int64()), pa.array(marks, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "n", "ka", "kb", "marks", "bands"])


def _sets(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """(id, s): the full shingle sets of the documents in ids (and of a few that its Bloom filter takes for them)."""
    two_hashes = lambda c: (F.xxhash64(c, F.lit(1)).alias("h1"), F.xxhash64(c, F.lit(2)).alias("h2"))
    wanted = bloom(ids.select(*two_hashes("id")))
    own = docs.select("doc_id", "text", *two_hashes("doc_id"))

    def sets(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hit = pa.array(may_contain(wanted.value, batch.column(2).to_numpy(), batch.column(3).to_numpy()))
            few = batch.select([0, 1]).filter(hit)
            for at, part in blocks(few.column(1).to_pylist()):
                got = [s.view(np.int64) for s in shingle_sets(part)]
                yield pa.RecordBatch.from_arrays([few.column(0).slice(at, len(part)), pa.array(got, pa.list_(pa.int64()))], ["id", "s"])

    return own.mapInArrow(sets, "id long, s array<long>")


def _confirmed(docs: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    """Those of pairs (a, b) whose full sets are similar enough."""
    full = _sets(docs, pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct())
    one = pairs.join(full.select(F.col("id").alias("a"), F.col("s").alias("sa")), "a")
    two = one.join(full.select(F.col("id").alias("b"), F.col("s").alias("sb")), "b")
    both = F.size(F.array_intersect("sa", "sb"))
    return two.filter(both * (100 + percent) >= percent * (F.size("sa") + F.size("sb"))).select("a", "b")


def _cells(percent: int):
    """Of rows (grp, low, high, block, id, own, n, marks, s) sorted by the first three: the links (a, b) in each cell.

    A cell holds two blocks (or one) of a group; compared are pairs of different components that share a band, and of two
    components only until a link joins them.
    """

    def links(rows: list[tuple]) -> Iterator[tuple[int, int]]:
        block, ids, own, n = (np.array([r[k] for r in rows]) for k in range(4))
        marks = np.stack([r[4] for r in rows])
        first = np.flatnonzero(block == block.min())
        second = first if block.min() == block.max() else np.flatnonzero(block == block.max())
        parent: dict[int, int] = {}

        def root(c: int) -> int:
            while parent.get(c, c) != c:
                c = parent[c] = parent.get(parent[c], parent[c])
            return c

        for low in range(0, len(first), 32):
            i = first[low : low + 32]
            equal = marks[i][:, None] == marks[second]
            near = (equal.mean(2) >= NEAR) & equal.reshape(len(i), len(second), BANDS, ROWS).all(3).any(2)
            near &= (own[i][:, None] != own[second]) & (100 * np.minimum(n[i][:, None], n[second]) >= percent * np.maximum(n[i][:, None], n[second]))
            if second is first:
                near &= i[:, None] < second
            for p, q in zip(*np.nonzero(near), strict=True):
                one, two = root(int(own[i[p]])), root(int(own[second[q]]))
                if one == two:
                    continue
                x, y = rows[i[p]][5], rows[second[q]][5]
                if len(np.intersect1d(x, y, assume_unique=True)) * (100 + percent) >= percent * (len(x) + len(y)):
                    parent[one] = two
                    yield int(ids[i[p]]), int(ids[second[q]])

    def meet(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def done():
            got = list(links(held)) if len({r[2] for r in held}) > 1 else []
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*got, strict=True)], ["a", "b"])

        for batch in batches:
            cols = [batch.column(k).to_pylist() for k in range(7)]
            for k, (grp, low, high, block, name, own, n) in enumerate(zip(*cols, strict=True)):
                if (grp, low, high) != now:
                    yield from done()
                    now, held = (grp, low, high), []
                held.append((block, name, own, n, np.frombuffer(batch.column(7)[k].as_buffer(), np.uint16), batch.column(8)[k].values.to_numpy()))
        yield from done()

    return meet


def near_duplicates(docs: DataFrame, text: str = "text", percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links), kept; one row per row of docs."""
    body = docs.select(column(docs, "doc_id", "long").alias("doc_id"), column(docs, text, "string").alias("text"))
    signed = cut(body.mapInArrow(_signatures, "doc_id long, n long, ka long, kb long, marks binary, bands array<long>"))
    linked = signed.filter("n > 0 and doc_id is not null")
    classes = linked.groupBy("ka", "kb").agg(F.min(F.struct("doc_id", "n", "marks", "bands")).alias("x")).select("ka", "kb", "x.*")
    classes = cut(classes)
    rows = classes.select("doc_id", F.explode("bands").alias("band"))
    buckets = rows.groupBy("band").agg(F.min("doc_id").alias("lead"), F.count("*").alias("c")).filter("c > 1").drop("c")
    shared = cut(rows.join(buckets, "band"))
    tried = cut(shared.filter("doc_id <> lead").select(F.col("doc_id").alias("a"), F.col("lead").alias("b")).distinct())
    edges = cut(_confirmed(body, tried, percent))
    found = components(edges)
    # buckets whose least document didn't link all: their documents meet again, in groups that share buckets
    owner = cut(shared.join(found, shared["doc_id"] == found["node"], "left").select("band", "doc_id", F.coalesce("component", "doc_id").alias("own")))
    held = owner.select("band", "own").distinct().groupBy("band").agg(F.count("*").alias("k")).filter("k > 1")
    mixed = cut(owner.join(held.select("band"), "band").join(buckets, "band"))
    if not mixed.isEmpty():
        groups = components(mixed.select(F.col("doc_id").alias("a"), F.col("lead").alias("b")).distinct())
        member = mixed.select("doc_id", "own").distinct().join(groups, F.col("doc_id") == F.col("node")).select("doc_id", "own", F.col("component").alias("grp"))
        size = member.groupBy("grp").agg(F.ceil(F.count("*") / CELL).cast("int").alias("blocks"))
        placed = member.join(size, "grp").withColumn("block", F.pmod(F.xxhash64("doc_id"), "blocks").cast("int")).select("grp", "block", "blocks", F.col("doc_id").alias("id"), "own")
        known = _sets(body, member.select(F.col("doc_id").alias("id")).distinct()).join(classes.select(F.col("doc_id").alias("id"), "n", "marks"), "id")
        held = placed.join(known, "id").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))  # one row each until here
        rows = held.select("grp", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high"), "block", "id", "own", "n", "marks", "s")
        dealt = rows.repartition(tasks(docs.sparkSession, 12), "grp", "low", "high").sortWithinPartitions("grp", "low", "high")
        more = cut(dealt.mapInArrow(_cells(percent), "a long, b long"))
        if not more.isEmpty():
            found = components(edges.union(more))
    reps = classes.select("ka", "kb", F.col("doc_id").alias("node")).join(found, "node", "left").select("ka", "kb", F.coalesce("component", "node").alias("component"))
    slim = signed.select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.col("ka")).alias("ka"), "kb")
    out = slim.join(reps, ["ka", "kb"], "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_representatives(docs: DataFrame, text: str = "text", percent: int = PERCENT) -> DataFrame:
    """docs with one document of each group, that of the smallest doc_id (all its rows); unlinked rows all stay."""
    gone = near_duplicates(docs, text, percent).filter("not kept").select(F.col("doc_id").alias("__id")).distinct()
    return docs.join(gone, docs["doc_id"] == F.col("__id"), "left_anti")


def op1_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


SQL = r"""
with recursive w as (
  select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws
  from documents),
g as (select doc_id, list_distinct(case when len(ws) >= 5 then list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))
             when len(ws) > 0 then [array_to_string(ws, ' ')] else [] end) as s from w),
c as (select list_sort(s) as k, min(doc_id) as rep, any_value(len(s)) as n from g where len(s) > 0 group by 1),
e as (select rep, n, unnest(k) as x from c),
p as (select a.rep as a, b.rep as b from e a join e b on a.x = b.x and a.rep < b.rep and 100 * least(a.n, b.n) >= 75 * greatest(a.n, b.n)
      group by a.rep, b.rep, a.n, b.n having 100 * count(*) >= 75 * (a.n + b.n - count(*))),
l as (select a, b from p union all select b, a from p),
r as (select rep as node, rep as seen from c union select l.b, r.seen from r join l on l.a = r.node and r.seen < l.b),
f as (select node, min(seen) as component from r group by node)
select g.doc_id, len(g.s)::bigint as n_shingles, coalesce(f.component, g.doc_id) as component_id, g.doc_id = coalesce(f.component, g.doc_id) as kept
from g left join c on c.k = list_sort(g.s) left join f on f.node = c.rep
"""
