"""Quality of texts: hashed word n-grams, logistic regression by follow-the-regularised-leader, sparse dot products.

Families of n-grams: words (1, 2), word shapes (1, 2, 3; runs of letters or digits count once) and repeats of the word
before.  Each family's counts are divided by their number, so length alone says nothing.  The model is fitted on at most
SAMPLE labelled documents (those of the smallest hash of doc_id outside the held-out third; 2 SAMPLE rows where doc_ids
repeat); every document is scored.
Null and empty texts get the score of no features (the bias); repeated rows get equal scores.  Labels that are null
count for nothing, several labels of one document as their mean over one half.  Without labels of both kinds each score
is 0.5.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import column, give_back, hash_sample, table
from longweave.llm.hashing import U, blocks, mix, ngrams, words_of

BITS, SAMPLE, EPOCHS, SCALE = 20, 6000, 3, 12.0
#: Byte classes of a shape: letters by case, digits, others as they are; bytes of longer characters count as small letters.
SHAPE = np.arange(256, dtype=np.uint8)
SHAPE[ord("A") : ord("Z") + 1], SHAPE[ord("a") : ord("z") + 1], SHAPE[ord("0") : ord("9") + 1], SHAPE[128:] = ord("X"), ord("x"), ord("9"), ord("x")
RUNS = np.isin(np.arange(256), [ord("X"), ord("x"), ord("9")])


def features(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each family: (slots of all its n-grams in text order, bounds of each text's, number of texts + 1)."""
    raw = [(x or "").encode("utf-8", "surrogatepass") for x in texts]
    whole = b"\n".join(raw)
    ends = np.cumsum([len(x) + 1 for x in raw])
    start, word = words_of(whole.lower())
    shape = SHAPE[np.frombuffer(whole, dtype=np.uint8)]
    keep = np.ones(len(shape), dtype=bool)
    keep[1:] = ~((shape[1:] == shape[:-1]) & RUNS[shape[1:]])
    form = words_of(shape[keep].tobytes())[1]  # as many words, in the same order
    bound = np.concatenate(([0], np.searchsorted(start, ends)))
    same = np.zeros(len(word), dtype=np.uint64)
    same[1:] = word[1:] == word[:-1]
    for family, (h, n) in enumerate(((word, 1), (word, 2), (form, 1), (form, 2), (form, 3), (same, 2))):
        grams = mix(ngrams(h, n) + U(family * 0x51ED27)) >> U(64 - BITS)
        of = np.repeat(np.arange(len(texts)), np.diff(bound))
        inside = of[: len(grams)] == of[n - 1 :][: len(grams)] if len(of) >= n else np.empty(0, bool)
        yield grams[inside].astype(np.int64), np.searchsorted(of[: len(grams)][inside], np.arange(len(texts) + 1)), inside


@dataclass
class Model:
    weight: np.ndarray
    bias: float

    def score(self, texts: list[str | None]) -> np.ndarray:
        out = np.full(len(texts), self.bias)
        for slots, bound, _ in features(texts):
            total = np.concatenate(([0.0], np.cumsum(self.weight[slots], dtype=np.float64)))
            n = np.diff(bound)
            out += SCALE * (total[bound[1:]] - total[bound[:-1]]) / np.maximum(n, 1)
        return 1 / (1 + np.exp(-np.clip(out, -40, 40)))


def sparse(texts: list[str | None]) -> list[tuple[np.ndarray, np.ndarray]]:
    """(slots, values) of each text."""
    parts: list[list] = [[] for _ in texts]
    for slots, bound, _ in features(texts):
        for i in range(len(texts)):
            if bound[i + 1] > bound[i]:
                s, c = np.unique(slots[bound[i] : bound[i + 1]], return_counts=True)
                parts[i].append((s, SCALE * c / (bound[i + 1] - bound[i])))
    out = []
    for p in parts:
        slot = np.concatenate([s for s, _ in p]) if p else np.empty(0, np.int64)
        value = np.concatenate([v for _, v in p]) if p else np.empty(0)
        at, inverse = np.unique(slot, return_inverse=True)
        out.append((at.astype(np.int32), np.bincount(inverse, value, len(at)).astype(np.float32)))
    return out


def ftrl(rows: Iterable[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, epochs: int = EPOCHS, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1, seed: int = 5) -> Model:
    """Per-coordinate FTRL-proximal updates, one example at a time, in a seeded order."""
    rows, z, n = list(rows), np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)
    if not len(labels) or labels.min() == labels.max():
        return Model(np.zeros(1 << BITS, dtype=np.float32), 0.0)
    order = np.random.default_rng(seed)
    share = labels.mean()  # the rarer label counts as much
    cost = np.where(labels > 0, 0.5 / share, 0.5 / (1 - share))

    def weights(at):
        return np.where(np.abs(z[at]) <= l1, 0.0, -(z[at] - np.sign(z[at]) * l1) / ((beta + np.sqrt(n[at])) / alpha + l2))

    for _ in range(epochs):
        for i in order.permutation(len(rows)):
            at, x = np.append(rows[i][0], 1 << BITS), np.append(rows[i][1], 1.0)
            w = weights(at)
            g = cost[i] * (1 / (1 + np.exp(-np.clip(w @ x, -40, 40))) - labels[i]) * x
            z[at] += g - (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / alpha * w
            n[at] += g * g
    w = weights(np.arange((1 << BITS) + 1))
    return Model(w[:-1].astype(np.float32), float(w[-1]))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", text: str = "text", sample: int = SAMPLE) -> Model:
    """Fitted on at most `sample` labelled documents; these rows and the weights are all that the driver holds."""
    known = labels.filter(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg((F.avg(label) > 0.5).cast("int").alias("y"))
    chosen = hash_sample(known, F.col("doc_id"), sample)  # the bound of what is broadcast
    body = docs.select("doc_id", column(docs, text, "string").alias("text")).join(F.broadcast(chosen), "doc_id")

    def extract(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, part in blocks(batch.column(1).to_pylist()):
                got = sparse(part)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(part)), batch.column(2).slice(at, len(part)), pa.array([s for s, _ in got], pa.list_(pa.int32())), pa.array([v for _, v in got], pa.list_(pa.float32()))], ["doc_id", "y", "slot", "value"])

    found = body.mapInArrow(extract, "doc_id long, y int, slot array<int>, value array<float>").withColumn("h", F.hash("slot", "value"))
    if body.count() > 2 * sample:  # doc_ids that repeat
        found = found.orderBy("doc_id", "h").limit(2 * sample)
    rows = found.toArrow().sort_by([("doc_id", "ascending"), ("h", "ascending")])
    model = ftrl(zip((x.values.to_numpy() for x in rows["slot"]), (x.values.to_numpy() for x in rows["value"]), strict=True), rows["y"].to_numpy().astype(float))
    del rows
    give_back()
    return model


def score_quality(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """docs with score (0 to 1) and predicted (1 if score >= 0.5, else 0)."""
    if text not in docs.columns:
        docs = docs.withColumn(text, F.lit(None).cast("string"))
    docs = docs.drop("score", "predicted")
    held, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text)

    def apply(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(at).to_pylist()
            p = np.concatenate([held.value.score(part) for _, part in blocks(texts)]) if texts else np.empty(0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p), pa.array((p >= 0.5).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    from pyspark.sql.types import StructType

    return docs.mapInArrow(apply, StructType([*docs.schema.fields, *StructType.fromDDL("score double, predicted int").fields]))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels").select("doc_id", "quality"))
    return score_quality(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
