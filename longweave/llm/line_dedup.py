"""Line dedup: an exact set-similarity self-join over all lines, removing later matches.

A line is the set of its distinct words (A-Z lowered, split at ASCII white space); a line without words takes no part.  A
line goes if an earlier one, by (doc_id, number of line), has the same set or a Jaccard similarity of at least PERCENT / 100.
Whether that earlier line goes too doesn't matter.  Sets below NEAR_LEAST words can only reach that by being equal.
The join: words are ordered by rarity (their count in the corpus, from a table of bounded size, then hash); two lines that
are similar enough share a word among the first n - ceil(t n) + 1 of each.  Candidates must pass the length filter, the
positional filter and a bitmap's bound on the difference, all lossless, and are verified on the full sets.  Equal sets are
one line from the start.  Where a line has more than FEW candidates under one word, its earliest FEW are verified first;
it then meets those of the rest that come before the match found, or all of the rest if there is none.
Null and empty texts have no lines; rows without doc_id take no part; rows that repeat a doc_id count as one document,
whose equal lines at the same place are one line.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import bloom, column, cut, may_contain, table, tasks
from longweave.llm.hashing import U, blocks, mix, words_of

PERCENT, FEW = 85, 8
#: A set of n words and another one are at most n / (n + 1) alike.
NEAR_LEAST = -(-PERCENT // (100 - PERCENT))
SLOTS, MOST_SLOTS, SPAN = 1 << 18, 1 << 22, 1 << 13
LINES, WORD_BITS, RARE_BITS = 1 << 13, 45, 6
SEEN, PAIRS = 200_000, 2_000_000
LINE = "doc_id long, line int, n int, ka long, kb long, counts array<int>"
PAIR = "la long, ea long, doc_id long, line int, from_doc long, token long, key long, post binary"
#: A posting in one binary value whose bytes sort by (n, ka, doc_id, line); doc_id is moved to be unsigned.
POST = np.dtype([("n", ">u4"), ("ka", ">u8"), ("doc_id", ">u8"), ("line", ">u4"), ("place", ">u4"), ("b0", ">u8"), ("b1", ">u8")])
SIGN = U(1 << 63)
#: A posting's key: its word, then its line's number of words as far as bits go.  Most comparisons of a sort end there.
SIZE_BITS = 63 - WORD_BITS


def block_lines(texts: list[str | None], counts: np.ndarray | None = None) -> Iterator[tuple]:
    """(text's number, line's number, n, ka, kb, first word's place, words) for runs of at most LINES lines.

    words: distinct 45-bit hashes, line by line, in order of rarity (counts: class of each slot, a power of two of them).
    """
    raw = [(x or "").encode("utf-8", "surrogatepass").lower() for x in texts]
    whole = b"\n".join(raw)
    start, h = words_of(whole)
    feeds = np.flatnonzero(np.frombuffer(whole, np.uint8) == 10)
    line = np.searchsorted(feeds, start)
    h = h >> U(64 - WORD_BITS)
    rare = np.zeros(len(h), np.uint64) if counts is None else counts[(h & U(len(counts) - 1)).astype(np.int64)].astype(np.uint64)
    first = np.concatenate(([0], np.cumsum([x.count(b"\n") + 1 for x in raw])))
    for low in range(0, len(feeds) + 1, LINES):
        a, z = np.searchsorted(line, (low, low + LINES))
        key = np.sort(((line[a:z] - low).astype(np.uint64) << U(WORD_BITS + RARE_BITS)) | (rare[a:z] << U(WORD_BITS)) | h[a:z])
        if not len(key):
            continue
        key = key[np.concatenate(([True], key[1:] != key[:-1]))]
        own = (key >> U(WORD_BITS + RARE_BITS)).astype(np.int64)
        word = key & U((1 << WORD_BITS) - 1)
        some, begin, n = np.unique(own, return_index=True, return_counts=True)
        ka, kb = np.add.reduceat(mix(word), begin), np.bitwise_xor.reduceat(mix(word + U(1 << 50)), begin)
        some = some + low
        doc = np.searchsorted(first, some, "right") - 1
        yield doc, some - first[doc], n, ka.view(np.int64), kb.view(np.int64), begin, word


def slots_for(docs: DataFrame) -> int:
    """Size of the rarity table: grows with the documents, within bounds.  Results don't depend on it."""
    return 1 << min(MOST_SLOTS.bit_length() - 1, max(SLOTS.bit_length() - 1, (docs.count() // 4).bit_length()))


def rarity(counts: DataFrame, slots: int) -> np.ndarray:
    """Class (0 for a count of one, then half powers of two) of each of the slots, from partial counts (line, counts)
    of SPAN slots each; a group has one row for each task, as many numbers as slots reach the driver."""

    def total(t):
        return pa.table({"line": t["line"].slice(0, 1), "counts": pa.array([np.sum([c.values.to_numpy() for c in t["counts"]], 0, dtype=np.int64)], pa.list_(pa.int64()))})

    out = np.zeros(slots, np.int64)
    for r in counts.groupBy("line").applyInArrow(total, "line int, counts array<long>").collect():
        out[r["line"] * SPAN : (r["line"] + 1) * SPAN] = r["counts"]
    return np.minimum(2 * np.log2(np.maximum(out, 1)), (1 << RARE_BITS) - 1).astype(np.uint8)


class Seen:
    """Line sets that this task has given out, with the earliest place; forgetting some only costs repeats."""

    def __init__(self):
        self.at: dict[int, tuple] = {}

    def new(self, ka: list[int], place: list[tuple]) -> np.ndarray:
        if len(self.at) > SEEN:
            self.at.clear()
        out, get = np.zeros(len(ka), bool), self.at.get
        for i, (k, p) in enumerate(zip(ka, place, strict=True)):
            if (old := get(k)) is None or p < old:
                self.at[k] = p
                out[i] = True
        return out


def _lines(slots: int):
    """The lines, and at the end this task's word counts, SPAN slots a row."""

    def emit(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, names = np.zeros(slots, np.int32), ["doc_id", "line", "n", "ka", "kb", "counts"]
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for at, part in blocks(batch.column(1).to_pylist()):
                for doc, line, n, ka, kb, _, word in block_lines(part):
                    total += np.bincount((word & U(slots - 1)).astype(np.int64), minlength=slots).astype(np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[at + doc]), pa.array(line, pa.int32()), pa.array(n, pa.int32()), pa.array(ka), pa.array(kb), pa.nulls(len(n), pa.list_(pa.int32()))], names)
        if total.any():
            k = slots // SPAN
            none = pa.nulls(k, pa.int64())
            yield pa.RecordBatch.from_arrays([none, pa.array(np.arange(k), pa.int32()), none.cast(pa.int32()), none, none, pa.array(list(total.reshape(k, SPAN)), pa.list_(pa.int32()))], names)

    return emit


def packed(rows: np.ndarray) -> pa.Array:
    """Rows of POST as binary values."""
    at = np.arange(len(rows) + 1, dtype=np.int32) * POST.itemsize
    return pa.Array.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(at), pa.py_buffer(rows.tobytes())])


def unpacked(values: pa.Array) -> np.ndarray:
    if not len(values):
        return np.empty(0, POST)
    kind = np.int64 if pa.types.is_large_binary(values.type) else np.int32
    first = int(np.frombuffer(values.buffers()[1], kind)[values.offset])
    return np.frombuffer(values.buffers()[2], POST, len(values), first)


def _postings(counts):
    """(key, post) of the words of each line's prefix; lines that this task has given out already don't come again."""

    def emit(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = Seen()
        for batch in batches:
            ids = batch.column(0).to_numpy()
            for at, part in blocks(batch.column(1).to_pylist()):
                for doc, line, n, ka, _, begin, word in block_lines(part, counts.value):
                    keep = n >= NEAR_LEAST
                    keep[keep] = seen.new(ka[keep].tolist(), list(zip(ids[at + doc[keep]].tolist(), line[keep].tolist(), strict=True)))
                    doc, line, n, ka, begin = (x[keep] for x in (doc, line, n, ka, begin))
                    if not len(n):
                        continue
                    every = np.repeat(begin - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum())
                    bit = (word[every] & U(127)).astype(np.int64)
                    one = U(1) << (bit & 63).astype(np.uint64)
                    cutsat = np.concatenate(([0], np.cumsum(n)[:-1]))
                    rows = np.empty(len(n), POST)
                    rows["n"], rows["ka"], rows["line"] = n, ka.view(np.uint64), line
                    rows["doc_id"] = ids[at + doc].view(np.uint64) ^ SIGN
                    rows["b0"], rows["b1"] = np.bitwise_or.reduceat(np.where(bit < 64, one, U(0)), cutsat), np.bitwise_or.reduceat(np.where(bit < 64, U(0), one), cutsat)
                    p = n - -(-PERCENT * n // 100) + 1
                    of = np.repeat(np.arange(len(n)), p)
                    place = np.arange(p.sum()) - np.repeat(np.cumsum(p) - p, p)
                    token = word[begin[of] + place]
                    common = counts.value[(token & U(len(counts.value) - 1)).astype(np.int64)] > 0  # a word met once has no partner
                    of, place, token = of[common], place[common], token[common].view(np.int64)
                    key = (token << SIZE_BITS) | np.minimum(n, (1 << SIZE_BITS) - 1)[of]
                    for k in range(0, len(of), 20_000):
                        out = rows[of[k : k + 20_000]]
                        out["place"] = place[k : k + 20_000]
                        yield pa.RecordBatch.from_arrays([pa.array(key[k : k + 20_000]), packed(out)], ["key", "post"])

    return emit


def _candidates(few: int | None, probing):
    """Of postings sorted by (key, post): pairs later, earlier of sets that pass all filters.

    doc_id, line: the earlier one's first place; from_doc: a document that holds the later one.
    few: at most so many, the earliest, for each later line and word.  A row without ea says that there are others under this
    word, the first of them at doc_id, line; the postings of these follow as rows with post.  Only such rows, or all if few
    is None, name the word.
    probing: a Bloom filter of the later lines wanted, or None for all.
    """
    names = [*POST.names, "token"]

    def ranges(lo: np.ndarray, n: np.ndarray, row: np.ndarray, to: np.ndarray | None) -> Iterator[tuple]:
        """Pairs of row[k] and the n[k] rows (to: numbers of rows) from lo[k], a bounded number at a time."""
        total, at = np.cumsum(n), 0
        while at < len(n):
            z = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + PAIRS, "right")))
            k = n[at:z]
            if k.sum():
                j = np.repeat(lo[at:z] - (np.cumsum(k) - k), k) + np.arange(k.sum())
                yield np.repeat(row[at:z], k), j if to is None else to[j]
            at = z

    def pairs_of(c: dict[str, np.ndarray], new_from: int, probe: np.ndarray | None) -> Iterator[tuple]:
        rank = np.cumsum(np.concatenate(([0], c["token"][1:] != c["token"][:-1])))
        comp = rank * (1 << 32) + c["n"]
        end = np.searchsorted(comp, rank * (1 << 32) + c["n"] * 100 // PERCENT, "right")
        row = np.arange(len(rank))
        begin = np.maximum(row + 1, new_from)  # pairs of rows that were there before are done
        if probe is None:
            parts = [ranges(begin, np.maximum(end - begin, 0), row, None)]
        else:  # one of the two is wanted
            some, other = np.flatnonzero(probe), np.flatnonzero(~probe)
            lo, hi = np.searchsorted(some, begin[other]), np.searchsorted(some, end[other])
            parts = [ranges(begin[some], np.maximum(end - begin, 0)[some], some, None), ranges(lo, np.maximum(hi - lo, 0), other, some)]
        for part in parts:
            for i, j in part:
                both = c["n"][i] + c["n"][j]
                need = -(-PERCENT * both // (100 + PERCENT))
                ok = np.minimum(c["n"][i] - c["place"][i], c["n"][j] - c["place"][j]) >= need
                i, j, slack = i[ok], j[ok], (both - 2 * need)[ok]
                ok = sum(np.bitwise_count(c[b][i] ^ c[b][j]).astype(np.int32) for b in ("b0", "b1")) <= slack
                i, j = i[ok], j[ok]
                swap = (c["doc_id"][i] > c["doc_id"][j]) | ((c["doc_id"][i] == c["doc_id"][j]) & (c["line"][i] > c["line"][j]))
                yield np.where(swap, i, j), np.where(swap, j, i)

    def earliest(c, later, earlier, nth_rest):
        """The few earliest partners of each later row; nth_rest gathers (later, earlier) of the others."""
        order = np.lexsort((c["line"][earlier], c["doc_id"][earlier], later))
        later, earlier = later[order], earlier[order]
        head = np.flatnonzero(np.concatenate(([True], later[1:] != later[:-1])))
        nth = np.arange(len(later)) - np.repeat(head, np.diff(np.append(head, len(later))))
        over = nth >= few
        if over.any():
            nth_rest.append((later[over], earlier[over], nth[over] == few))
        return later[~over], earlier[~over]

    signed = lambda x: pa.array(x.view(np.int64))
    place_of = lambda c, j: [pa.array((c["doc_id"][j] ^ SIGN).view(np.int64)), pa.array(c["line"][j].astype(np.int32))]
    fields = ["la", "ea", "doc_id", "line", "from_doc", "token", "key", "post"]

    def out(c, later, earlier, rest) -> Iterator[pa.RecordBatch]:
        none = lambda n, t=pa.int64(): pa.nulls(n, t)
        for at in range(0, len(later), 50_000):
            i, j = later[at : at + 50_000], earlier[at : at + 50_000]
            yield pa.RecordBatch.from_arrays([signed(c["ka"][i]), signed(c["ka"][j]), *place_of(c, j), place_of(c, i)[0], pa.array(c["token"][i]) if few is None else none(len(i)), none(len(i)), none(len(i), pa.binary())], fields)
        if rest:
            i, j, first = (np.concatenate(x) for x in zip(*rest, strict=True))
            saved = np.unique(np.concatenate([i, j]))
            i, j = i[first], j[first]
            if len(i):
                yield pa.RecordBatch.from_arrays([signed(c["ka"][i]), none(len(i)), *place_of(c, j), none(len(i)), pa.array(c["token"][i]), none(len(i)), none(len(i), pa.binary())], fields)
            rows = np.empty(len(saved), POST)
            for k in POST.names:
                rows[k] = c[k][saved]
            yield pa.RecordBatch.from_arrays([*(none(len(saved)) for _ in range(3)), none(len(saved), pa.int32()), none(len(saved)), pa.array(c["token"][saved]), pa.array((c["token"][saved] << SIZE_BITS) | np.minimum(c["n"][saved], (1 << SIZE_BITS) - 1)), packed(rows)], fields)

    def join(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = unpacked(batch.column(1))
            c = {k: rows[k].astype(np.int64 if k in ("n", "place", "line") else np.uint64) for k in POST.names}
            c["token"] = batch.column(0).to_numpy() >> SIZE_BITS
            old = 0
            if held is not None:
                old = len(held["token"])
                c = {k: np.concatenate([held[k], c[k]]) for k in names}
            once = np.concatenate(([True], (c["ka"][1:] != c["ka"][:-1]) | (c["token"][1:] != c["token"][:-1])))
            new_from = int(once[:old].sum())
            c = {k: v[once] for k, v in c.items()}
            probe = None if probing is None else may_contain(probing.value, c["ka"].view(np.int64), c["ka"].view(np.int64) >> 21)
            later, earlier, rest, size = [], [], [], 0
            for i, j in pairs_of(c, new_from, probe):
                if probe is not None:
                    i, j = i[probe[i]], j[probe[i]]
                later.append(i)
                earlier.append(j)
                size += len(i)
                if size > PAIRS:  # what is held stays bounded
                    i, j = np.concatenate(later), np.concatenate(earlier)
                    if few is None:
                        yield from out(c, i, j, [])
                        i = j = i[:0]
                    else:
                        i, j = earliest(c, i, j, rest)
                    later, earlier, size = [i], [j], 0
            if later:
                i, j = np.concatenate(later), np.concatenate(earlier)
                if few is not None and len(i):
                    i, j = earliest(c, i, j, rest)
                yield from out(c, i, j, rest)
            last = (c["token"] == c["token"][-1]) & (c["n"] * 100 >= PERCENT * c["n"][-1])  # what later rows can still meet
            held = {k: v[last] for k, v in c.items()}

    return join


def _verified(docs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(la, lb, doc_id, line) of those of pairs (la, ea, doc_id, line, from_doc) whose full sets are similar enough.

    Sets are made again from the documents that the pairs name; they carry the second half of their key.
    """
    wanted = bloom(pairs.select(F.explode(F.array("la", "ea")).alias("h1")).distinct().withColumn("h2", F.shiftright("h1", 21)))
    two_hashes = lambda c: (F.xxhash64(c, F.lit(1)).alias("h1"), F.xxhash64(c, F.lit(2)).alias("h2"))
    holders = bloom(pairs.select(F.explode(F.array("doc_id", "from_doc")).alias("d")).distinct().select(*two_hashes("d")))
    pairs = pairs.drop("from_doc").distinct()

    def sets(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = Seen()
        for batch in batches:
            few = batch.column(0).filter(pa.array(may_contain(holders.value, batch.column(1).to_numpy(), batch.column(2).to_numpy())))
            for _, part in blocks(few.to_pylist()):
                for _, _, n, ka, kb, begin, word in block_lines(part):
                    hit = np.flatnonzero((n >= NEAR_LEAST) & may_contain(wanted.value, ka, ka >> 21))
                    hit = hit[seen.new(ka[hit].tolist(), [()] * len(hit))]
                    if len(hit):
                        yield pa.RecordBatch.from_arrays([pa.array(ka[hit]), pa.array(kb[hit]), pa.array([word[begin[i] : begin[i] + n[i]].view(np.int64) for i in hit], pa.list_(pa.int64()))], ["ka", "kb", "s"])

    full = docs.select("text", *two_hashes("doc_id")).mapInArrow(sets, "ka long, kb long, s array<long>").repartition("ka").dropDuplicates(["ka", "kb"])
    one = pairs.join(full.select(F.col("ka").alias("la"), F.col("kb").alias("lb"), F.col("s").alias("x")), "la")
    two = one.join(full.select(F.col("ka").alias("ea"), F.col("s").alias("y")), "ea")
    both = F.size(F.array_intersect("x", "y"))
    return two.filter(both * (100 + PERCENT) >= PERCENT * (F.size("x") + F.size("y"))).select("la", "lb", "doc_id", "line")


def repeated_lines(docs: DataFrame, text: str = "text") -> DataFrame:
    """The lines to remove: doc_id, line (from 0), n_words (distinct), of_doc_id, of_line (the earliest match)."""
    spark = docs.sparkSession
    body = docs.select(column(docs, "doc_id", "long").alias("doc_id"), column(docs, text, "string").alias("text")).filter("doc_id is not null")
    slots = slots_for(body)
    both = cut(body.mapInArrow(_lines(slots), LINE))
    lines = both.filter("doc_id is not null").drop("counts")
    place = F.struct("doc_id", "line")
    firsts = lines.groupBy("ka", "kb").agg(F.min(place).alias("first"), F.max(place).alias("last"))
    counts = spark.sparkContext.broadcast(rarity(both.filter("doc_id is null").select("line", "counts"), slots))

    def met(postings, few, probing):
        dealt = postings.repartition(tasks(spark, 12) * 2, F.shiftright("key", SIZE_BITS)).sortWithinPartitions("key", "post")
        return dealt.mapInArrow(_candidates(few, probing), PAIR)

    def earliest(pairs):
        return cut(_verified(body, pairs).groupBy("la", "lb").agg(F.min(place).alias("of")))

    mate = ["la", "ea", "doc_id", "line", "from_doc"]
    found = cut(met(body.mapInArrow(_postings(counts), "key long, post binary"), FEW, None))
    near = earliest(found.filter("ea is not null").select(mate).distinct())
    others = found.filter("la is not null and ea is null").groupBy("la", "token").agg(F.min(place).alias("since"))
    left = cut(others.join(near.drop("lb"), "la", "left").filter("of is null or since < of"))
    if not left.isEmpty():  # lines whose earliest match may be among what was put off meet that part
        probing = bloom(left.select(F.col("la").alias("h1"), F.shiftright("la", 21).alias("h2")).distinct())
        again = found.filter("post is not null").join(left.select("token").distinct(), "token", "left_semi").select("key", "post")
        rest = met(again, None, probing).select(*mate, "token").join(left, ["la", "token"]).filter((place >= F.col("since")) & (F.col("of").isNull() | (place < F.col("of"))))
        near = near.union(earliest(cut(rest.select(mate).distinct())))
    matched = near.groupBy(F.col("la").alias("ka"), F.col("lb").alias("kb")).agg(F.min("of").alias("of"))
    known = firsts.join(matched, ["ka", "kb"], "left").filter("of is not null or first <> last").select("ka", "kb", F.col("first"), F.col("of"))
    gone = lines.join(known, ["ka", "kb"]).filter("of is not null or first <> struct(doc_id, line)")
    source = F.coalesce("of", "first")
    return gone.select("doc_id", "line", F.col("n").alias("n_words"), source["doc_id"].alias("of_doc_id"), source["line"].alias("of_line"))


def remove_repeated_lines(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs without the repeated lines; n_chars, if there, counts anew.  Documents that lose all their words go."""
    if text not in docs.columns or "doc_id" not in docs.columns:
        return docs
    gone = repeated_lines(docs, text).groupBy("doc_id").agg(F.collect_set("line").alias("__gone")).withColumnRenamed("doc_id", "__id")
    both = docs.join(gone, docs["doc_id"] == F.col("__id"), "left")
    less = F.array_join(F.expr(f"filter(split(`{text}`, '\\n', -1), (x, i) -> not array_contains(__gone, i))"), "\n")
    whole = F.col("__gone").isNull() | F.col(text).isNull()
    out = both.withColumn("__text", F.when(whole, F.col(text)).otherwise(less)).filter(whole | F.col("__text").rlike(r"[^\x20\x09-\x0D]"))
    size = F.when(whole, F.col("n_chars")).otherwise(F.length("__text").cast("long")) if "n_chars" in docs.columns else None
    new = {text: F.col("__text"), "n_chars": size}
    return out.select(*(new.get(c, F.col(c)).alias(c) for c in docs.columns))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


SQL = r"""
with l as (select doc_id, unnest(range(len(string_split(text, chr(10)))))::int as line, unnest(string_split(text, chr(10))) as x from documents where text is not null and doc_id is not null),
w as (select doc_id, line, list_sort(list_distinct(list_filter(regexp_split_to_array(translate(x, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda y: y <> ''))) as s from l),
f as (select s, len(s) as n, min({'d': doc_id, 'l': line}) as first, row_number() over () as k from w where len(s) > 0 group by s),
e as (select k, n, first, unnest(s) as x from f),
p as (select a.k, min(b.first) as of from
       (select a.k as ak, b.k as bk from e a join e b on a.x = b.x and a.first > b.first and 100 * least(a.n, b.n) >= 85 * greatest(a.n, b.n)
        group by a.k, b.k, a.n, b.n having 185 * count(*) >= 85 * (a.n + b.n)) q join f a on a.k = q.ak join f b on b.k = q.bk group by a.k)
select w.doc_id, w.line, len(w.s)::int as n_words, coalesce(p.of, f.first).d as of_doc_id, coalesce(p.of, f.first).l as of_line
from w join f on w.s = f.s left join p on p.k = f.k where p.of is not null or f.first <> {'d': w.doc_id, 'l': w.line}
"""
