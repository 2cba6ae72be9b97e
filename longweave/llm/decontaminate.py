"""Benchmark decontamination by greedy string tiling.

Words are lower-cased (A-Z) with ASCII punctuation as separators.  Seeds are the LEAST-word windows of the benchmark's
items; a document that shares seeds with an item is tiled against it: the longest common unmarked runs (Karp-Rabin, search
length halved from the item's length to LEAST) are marked first and never overlap.  A pair whose tiles cover at least
COVERAGE of the item's words is a match, in whatever order the tiles stand.
Tiles lie within shared seeds, so only these parts of a document are tiled, and a pair whose seeds cover too little of the
item is skipped: neither loses a match.  Items of fewer than LEAST words, null and empty texts match nothing.  Repeated
items or documents give repeated rows.  A benchmark over CHUNK_CHARS characters is taken in slices by hash of its item,
one pass over the documents for each; one slice's index is broadcast at a time.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from longweave.llm.common import column, cut, table
from longweave.llm.hashing import BASE, U, blocks, ngrams, words_of

LEAST, COVERAGE, CHUNK_CHARS = 5, 0.6, 20_000_000
PLAIN = bytes(32 if c < 128 and not chr(c).isalnum() else c + 32 if 65 <= c <= 90 else c for c in range(256))


def tokens(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    raw = [(x or "").encode("utf-8", "surrogatepass").translate(PLAIN) for x in texts]
    start, h = words_of(b"\n".join(raw))
    return h, np.concatenate(([0], np.searchsorted(start, np.cumsum([len(x) + 1 for x in raw]))))


def _windows(h: np.ndarray, s: int) -> np.ndarray:
    """Karp-Rabin hash of each window of s tokens, from one prefix sum."""
    p = np.zeros(len(h) + 1, dtype=np.uint64)
    np.cumsum(h * _power(len(h)), out=p[1:], dtype=np.uint64)
    return (p[s:] - p[:-s]) * _power(len(h), UNBASE)[: len(h) - s + 1]  # each brought to the power of place 0


#: The inverse of BASE modulo 2**64.
UNBASE = U(pow(int(BASE), -1, 2**64))


def _power(n: int, base: np.uint64 = BASE) -> np.ndarray:
    return np.cumprod(np.concatenate(([U(1)], np.full(max(0, n - 1), base, dtype=np.uint64))), dtype=np.uint64)[:n]


def tile(item: np.ndarray, doc: np.ndarray, least: int = LEAST) -> list[tuple[int, int, int]]:
    """Greedy tiles (place in item, place in doc, length), longest first, none overlapping on either side."""
    free_i, free_d = np.ones(len(item), bool), np.ones(len(doc), bool)
    out: list[tuple[int, int, int]] = []
    s = len(item)

    def starts(s: int) -> tuple[np.ndarray, np.ndarray]:
        """Where unmarked runs of s equal tokens begin that none to their left continues."""
        wi, wd = _windows(item, s), _windows(doc, s)
        open_i = np.flatnonzero(np.convolve(free_i, np.ones(s), "valid") > s - 0.5)
        open_d = np.flatnonzero(np.convolve(free_d, np.ones(s), "valid") > s - 0.5)
        open_d = open_d[np.isin(wd[open_d], wi[open_i])]
        found = []
        for at in range(0, len(open_d), max(1, 2_000_000 // max(1, len(open_i)))):
            d = open_d[at : at + max(1, 2_000_000 // max(1, len(open_i)))]
            k, j = np.nonzero(wd[d][:, None] == wi[open_i])
            i, d = open_i[j], d[k]
            before = (i > 0) & (d > 0)
            before &= free_i[i - 1] & free_d[d - 1] & (item[i - 1] == doc[d - 1])
            found.append((i[~before], d[~before]))
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.empty(0, np.int64),) * 2

    while s >= least:
        found = []
        if s <= min(len(item), len(doc)):
            for i, d in zip(*(x.tolist() for x in starts(s)), strict=True):
                most = min(len(item) - i, len(doc) - d)
                same = (item[i : i + most] == doc[d : d + most]) & free_i[i : i + most] & free_d[d : d + most]
                n = most if same.all() else int(same.argmin())
                if n >= s:  # equal hashes alone are no match
                    found.append((n, i, d))
        longest = max((f[0] for f in found), default=0)
        if longest > 2 * s:  # a much longer run: search at its length first
            s = longest
            continue
        cut_short = False
        for n, i, d in sorted(found, key=lambda f: (-f[0], f[1], f[2])):
            free = free_i[i : i + n] & free_d[d : d + n]
            if free.all():
                free_i[i : i + n] = free_d[d : d + n] = False
                out.append((i, d, n))
            elif np.convolve(free, np.ones(s), "valid").max() > s - 0.5:
                cut_short = True  # what a tile left of this run may be longer than the runs that follow
                break
        if cut_short:
            continue
        s = s // 2 if s > 2 * least else least if s > least else 0
    return out


@dataclass
class Index:
    """Seeds of the items, sorted, with where each stands (item, place)."""

    ids: list
    items: list[np.ndarray]
    seeds: np.ndarray
    bound: np.ndarray
    item: np.ndarray
    place: np.ndarray

    @classmethod
    def of(cls, ids: list, texts: list[str | None]) -> Index:
        h, bound = tokens(texts)
        items = [h[a:z] for a, z in zip(bound[:-1], bound[1:], strict=True)]
        grams = [ngrams(x, LEAST) for x in items]
        key = np.concatenate([*grams, np.empty(0, np.uint64)])
        item = np.repeat(np.arange(len(items)), [len(g) for g in grams])
        place = np.concatenate([*(np.arange(len(g)) for g in grams), np.empty(0, np.int64)])
        order = np.argsort(key, kind="stable")
        seeds, first = np.unique(key[order], return_index=True)
        return cls(ids, items, seeds, np.append(first, len(key)), item[order], place[order].astype(np.int64))

    def match(self, texts: list[str | None], coverage: float) -> Iterator[tuple[int, int, int, int, int]]:
        """(text's number, item's number, covered words, item's words, tiles) of each match."""
        h, bound = tokens(texts)
        if not len(self.seeds) or len(h) < LEAST:
            return
        grams = ngrams(h, LEAST)
        at = np.minimum(np.searchsorted(self.seeds, grams), len(self.seeds) - 1)
        hit = np.flatnonzero(self.seeds[at] == grams)
        doc = np.searchsorted(bound, hit, "right") - 1
        inside = hit + LEAST <= bound[doc + 1]
        hit, doc = hit[inside], doc[inside]
        for k in np.unique(doc).tolist():
            own = hit[doc == k]
            seed = at[own]
            n = self.bound[seed + 1] - self.bound[seed]
            flat = np.repeat(self.bound[seed] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
            item, place, where = self.item[flat], self.place[flat], np.repeat(own, n)
            order = np.argsort(item, kind="stable")
            some, first = np.unique(item[order], return_index=True)
            for i, group in zip(some.tolist(), np.split(order, first[1:]), strict=True):
                size = len(self.items[i])
                cover = np.zeros(size, bool)
                cover[(place[group][:, None] + np.arange(LEAST)).ravel()] = True
                if cover.sum() < coverage * size:
                    continue
                part = np.unique((where[group][:, None] + np.arange(LEAST)).ravel())
                gaps = np.flatnonzero(np.diff(part) > 1) + 1
                text = np.insert(h[part], gaps, np.arange(len(gaps)).astype(np.uint64))  # tells the parts from each other
                tiles = tile(self.items[i], text)
                covered = sum(t[2] for t in tiles)
                if covered >= coverage * size:
                    yield k, i, covered, size, len(tiles)


def _indexes(benchmark: DataFrame, chunk_chars: int):
    """(number of slices, an iterator of their broadcast indexes)."""
    own = benchmark.select(column(benchmark, "item_id", "long").alias("item_id"), column(benchmark, "text", "string").alias("text"))
    size = own.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    n = max(1, -(-size // chunk_chars))

    def each():
        for i in range(n):
            rows = own.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == i).orderBy("item_id", "text").collect()
            yield benchmark.sparkSession.sparkContext.broadcast(Index.of([r["item_id"] for r in rows], [r["text"] for r in rows]))

    return n, each()


def _matches(docs: DataFrame, benchmark: DataFrame, text: str, coverage: float, chunk_chars: int) -> DataFrame:
    """The rows of contamination(), with the text's hash.  Of several slices only one is held at a time: each is matched,
    its few matches written, its broadcast destroyed."""
    body = docs.select(column(docs, "doc_id", "long").alias("doc_id"), column(docs, text, "string").alias("text")).withColumn("key", F.xxhash64("text"))
    names = ["doc_id", "item_id", "covered", "item_words", "tiles", "coverage", "key"]
    n, held_each = _indexes(benchmark, chunk_chars)
    out = None
    for held in held_each:

        def find(batches: Iterable[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids, keys = batch.column(0).to_pylist(), batch.column(2).to_pylist()
                for at, part in blocks(batch.column(1).to_pylist()):
                    got = [(ids[at + k], held.value.ids[i], c, n, t, c / n, keys[at + k]) for k, i, c, n, t in held.value.match(part, coverage)]
                    if got:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*got, strict=True), (*(pa.int64(),) * 5, pa.float64(), pa.int64()), strict=True)], names)

        part = body.mapInArrow(find, "doc_id long, item_id long, covered long, item_words long, tiles long, coverage double, key long")
        if n > 1:
            part = cut(part)
            held.destroy()
        out = part if out is None else out.union(part)
    return out


def contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", coverage: float = COVERAGE, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """One row for each document and item that match: doc_id, item_id, covered, item_words, tiles, coverage."""
    return _matches(docs, benchmark, text, coverage, chunk_chars).drop("key")


def decontaminate(docs: DataFrame, benchmark: DataFrame, text: str = "text", coverage: float = COVERAGE, chunk_chars: int = CHUNK_CHARS) -> DataFrame:
    """docs without the rows that match an item; with one slice in one pass without a shuffle."""
    if text not in docs.columns:
        return docs
    at = docs.columns.index(text)
    n, held_each = _indexes(benchmark, chunk_chars)
    if n > 1:
        gone = _matches(docs, benchmark, text, coverage, chunk_chars).select("key").distinct()  # equal texts match alike
        return docs.join(gone, F.xxhash64(docs[text].cast("string")) == F.col("key"), "left_anti")
    held = next(held_each)

    def keep(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = np.ones(batch.num_rows, bool)
            for first, part in blocks(batch.column(at).to_pylist()):
                for k, *_ in held.value.match(part, coverage):
                    clean[first + k] = False
            yield batch.filter(pa.array(clean))

    return docs.mapInArrow(keep, StructType(docs.schema.fields))


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
