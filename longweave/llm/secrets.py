"""Secrets in texts: patterns give the base set, a character convolutional network judges every other candidate.

The network (numpy) reads a candidate with the characters around it; a candidate longer than CORE characters in steps of
half as many, of which the highest score counts.  It is trained on labelled findings: seeded examples
of public credential formats and of look-alikes, and the base findings of at most SAMPLE_DOCS documents (those with any
of ten times as many of smallest hash of text), wherever they stand in the text.  Other candidates of the documents are
unknown, so they get no label.  Held-out findings calibrate its output (Platt scaling); the threshold is the highest that
still finds RECALL of the held-out secrets that no base pattern meets.
Null and empty texts have no spans; repeated rows keep one result each; other columns of the input pass through.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import column, table

KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
#: Runs are maximal, so asking for the length in the pattern keeps the same matches.
ACCESS, HEX = re.compile(r"AKIA[A-Z0-9]{16,}"), re.compile(r"[0-9a-f]{24,}")
WORDS = ("passw", "secret", "token", "api")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
DIGIT = re.compile(r"[0-9]")
LEFT, CORE, RIGHT = 24, 48, 8
WIDTH = LEFT + CORE + RIGHT
SAMPLE_DOCS, DOC_SPANS, RECALL, MODEL_KIND = 2000, 20, 0.95, "model"
SPAN = "array<struct<kind:string,start:int,end:int,score:double>>"


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, end, kind's index), by start, then kind."""
    out = []
    low = text.lower()
    if any(w in low for w in WORDS):
        out += [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text)]
    out += [(m.start(), m.end(), 2) for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], s[2]))


def other_candidates(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int]]:
    """Runs of 16 or more key characters with a digit that no base span overlaps."""
    found = [m.span() for m in CANDIDATE.finditer(text) if DIGIT.search(m.group())]
    return [(a, z) for a, z in found if not any(a < e and s < z for s, e, _ in base)]


def views(start: int, end: int) -> list[tuple[int, int]]:
    """What the network reads of a candidate: runs of at most CORE characters, the last one up to its end."""
    if end - start <= CORE:
        return [(start, end)]
    return [(a, a + CORE) for a in range(start, end - CORE, CORE // 2)] + [(end - CORE, end)]


def encode(text: str, start: int, end: int) -> np.ndarray:
    """Character classes of a run of at most CORE characters and its context: 0 pad, 1-95 printable ASCII, 96 other; +97
    inside."""
    out = np.zeros(WIDTH, dtype=np.uint8)
    for at, piece, inside in ((LEFT - min(LEFT, start), text[max(0, start - LEFT) : start], 0), (LEFT, text[start : min(end, start + CORE)], 97), (LEFT + CORE, text[end : end + RIGHT], 0)):
        code = np.frombuffer(piece.encode("latin-1", "replace"), dtype=np.uint8)
        out[at : at + len(code)] = np.where((code >= 32) & (code < 127), code - 31, 96) + inside
    return out


@dataclass
class CharCNN:
    """Embedding, one convolution with ReLU, maximum and mean over places, a logistic output, Platt's two numbers."""

    emb: np.ndarray  # 194 x d
    conv: np.ndarray  # (k d) x f
    bias: np.ndarray
    out: np.ndarray  # 2 f + 1
    scale: float = 1.0
    shift: float = 0.0
    threshold: float = 0.5
    k = 5

    @classmethod
    def fresh(cls, d: int = 8, f: int = 16, seed: int = 7) -> CharCNN:
        g = np.random.default_rng(seed)
        return cls(*(x.astype(np.float32) for x in (g.normal(0, 0.3, (194, d)), g.normal(0, (2 / (cls.k * d)) ** 0.5, (cls.k * d, f)), np.zeros(f), g.normal(0, 0.1, 2 * f + 1))))

    def forward(self, x: np.ndarray):
        e = self.emb[x]
        n, w, d = e.shape
        win = np.lib.stride_tricks.sliding_window_view(e.reshape(n, w * d), self.k * d, axis=1)[:, ::d]
        z = np.maximum(win @ self.conv + self.bias, 0)
        top = z.argmax(1)
        feats = np.concatenate([z.max(1), z.mean(1), np.ones((n, 1), np.float32)], 1)
        return win, z, top, feats, feats @ self.out

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([self.forward(x[i : i + 512])[4] for i in range(0, len(x), 512)]) if len(x) else np.empty(0)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.scale * self.logit(x).astype(np.float64) + self.shift, -40, 40)))

    def train(self, x: np.ndarray, y: np.ndarray, epochs: int = 6, rate: float = 4e-3, seed: int = 11) -> None:
        g, names = np.random.default_rng(seed), ("emb", "conv", "bias", "out")
        mean, var, step = ({k: np.zeros_like(getattr(self, k)) for k in names} for _ in range(2)), None, 0
        mean, var = tuple(mean)
        for _ in range(epochs):
            for at in np.array_split(g.permutation(len(x)), max(1, len(x) // 64)):
                win, z, top, feats, logit = self.forward(x[at])
                n, w, f = z.shape
                err = ((1 / (1 + np.exp(-np.clip(logit, -40, 40))) - y[at]) / n).astype(np.float32)
                back = err[:, None] * self.out
                dz = np.repeat(back[:, None, f : 2 * f] / w, w, 1)
                np.put_along_axis(dz, top[:, None], np.take_along_axis(dz, top[:, None], 1) + back[:, None, :f], 1)
                dz *= z > 0
                flat = dz.reshape(-1, f)
                demb = np.zeros_like(self.emb)
                dwin = (flat @ self.conv.T).reshape(n, w, self.k, -1)
                for j in range(self.k):
                    np.add.at(demb, x[at][:, j : j + w], dwin[:, :, j])
                step += 1
                for k, grad in zip(names, (demb, win.reshape(-1, self.conv.shape[0]).T @ flat, flat.sum(0), feats.T @ err), strict=True):
                    mean[k] += 0.1 * (grad - mean[k])
                    var[k] += 0.001 * (grad * grad - var[k])
                    getattr(self, k)[...] -= rate * (mean[k] / (1 - 0.9**step)) / (np.sqrt(var[k] / (1 - 0.999**step)) + 1e-8)

    def calibrate(self, x: np.ndarray, y: np.ndarray, recall: float = RECALL, binding: np.ndarray | None = None) -> None:
        """Platt scaling by Newton steps on held-out findings, then the highest threshold that keeps this recall.

        binding: which of the findings the recall is about; all if None.
        """
        z, a, b = self.logit(x).astype(np.float64), 1.0, 0.0
        t = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / ((1 - y).sum() + 2))
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(a * z + b, -40, 40)))
            w = p * (1 - p) + 1e-9
            grad = np.array([((p - t) * z).sum() + 1e-3 * (a - 1), (p - t).sum()])
            hess = np.array([[(w * z * z).sum() + 1e-3, (w * z).sum()], [(w * z).sum(), w.sum() + 1e-6]])
            step = np.linalg.solve(hess, grad)
            a, b = a - np.clip(step[0], -1, 1), b - np.clip(step[1], -1, 1)
        self.scale, self.shift = float(a), float(b)
        own = np.sort(self.score(x[y > 0 if binding is None else (y > 0) & binding]))
        self.threshold = float(own[int((1 - recall) * len(own))]) if len(own) else 0.5


def seeded_findings(n: int = 1500, seed: int = 3) -> list[tuple[str, int, int, int]]:
    """(text, start, end, label): public credential formats and their look-alikes, in made-up surroundings."""
    g = np.random.default_rng(seed)
    alnum, hexa = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "0123456789abcdef"
    pick = lambda chars, k: "".join(chars[i] for i in g.integers(0, len(chars), k))
    syllables = ["an", "the", "re", "on", "sch", "eau", "ción", "ent", "li", "mo", "ta", "ver", "ing"]
    word = lambda: "".join(syllables[i] for i in g.integers(0, len(syllables), int(g.integers(1, 4))))
    secret = [lambda: "ghp_" + pick(alnum, 36), lambda: "xoxb-" + pick("0123456789", 12) + "-" + pick(alnum, 24), lambda: "sk_live_" + pick(alnum, 24), lambda: "eyJ" + pick(alnum + "_-", 40), lambda: "AIza" + pick(alnum + "_-", 35), lambda: pick(alnum + "+/", 40), lambda: "AKIA" + pick(alnum[:26] + "0123456789", 16), lambda: pick(hexa, int(g.choice([32, 40, 64])))]
    plain = [lambda: "-".join(word() for _ in range(5)) + "-" + pick("0123456789", 2), lambda: "/" + "/".join(word() for _ in range(5)) + "/" + pick("0123456789", 4), lambda: pick("0123456789", int(g.integers(16, 24))), lambda: "".join(word().title() for _ in range(6)) + pick("0123456789", 1), lambda: "20" + pick("012", 2) + "-" + pick("01", 2) + "-" + pick("012", 2) + "T" + pick("012", 2) + "-00-00", lambda: "=" * 16 + pick("0123456789", 1), lambda: "_".join(word() for _ in range(5)) + pick("0123456789", 1)]
    lead = {1: ["key = ", "Authorization: ", "export VALUE=", 'auth="', "", "bearer ", "use "], 0: ["see ", "page ", "in ", "", "from ", "id ", "at "]}
    out = []
    for i in range(n):
        label = i % 2
        body = (secret if label else plain)[int(g.integers(0, len(secret if label else plain)))]()
        head = " ".join(word() for _ in range(4)) + " " + lead[label][int(g.integers(0, 7))]
        out.append((head + body + " " + " ".join(word() for _ in range(3)), len(head), len(head) + len(body), label))
    return out


def base_windows(text: str) -> list[bytes]:
    """Encoded base findings of the whole text, at most DOC_SPANS, evenly spread."""
    base = base_spans(text)
    return [encode(text, s, e).tobytes() for s, e, _ in base[:: max(1, -(-len(base) // DOC_SPANS))]]


def train_model(docs: DataFrame, text: str = "text", sample_docs: int = SAMPLE_DOCS) -> CharCNN:
    """The trained, calibrated network; windows of at most sample_docs texts come to the driver."""

    def windows(batches):
        for batch in batches:
            got = [base_windows(t) for t in batch.column(0).to_pylist()]
            some = [i for i, w in enumerate(got) if w]
            yield pa.RecordBatch.from_arrays([batch.column(1).take(pa.array(some, pa.int64())), pa.array([got[i] for i in some], pa.list_(pa.binary()))], ["key", "x"])

    texts = docs.select(column(docs, text, "string").alias("t")).filter("t is not null")
    share = min(1.0, (13 * sample_docs + 100) / max(1, texts.count()))  # texts stay where they are; their windows travel
    some = texts.withColumn("key", F.xxhash64("t")).filter(F.pmod("key", F.lit(1 << 40)) < int(share * (1 << 40)))
    near = some.mapInArrow(windows, "key long, x array<binary>")
    seen = [np.frombuffer(w, np.uint8) for r in near.orderBy(F.pmod("key", F.lit(1 << 40)), "x").limit(sample_docs).collect() for w in r["x"]]
    seeds = seeded_findings()
    x = np.stack([*(encode(t, a, z) for t, a, z, _ in seeds), *seen])
    y = np.array([label for *_, label in seeds] + [1] * len(seen), dtype=np.float32)
    new = np.zeros(len(x), bool)  # not met by a base pattern
    new[: len(seeds)] = [not any(a < e and s < z for s, e, _ in base_spans(t)) for t, a, z, _ in seeds]
    held = np.arange(len(x)) % 4 == 3
    held[: len(seeds)] = (np.arange(len(seeds)) // 2) % 4 == 3
    model = CharCNN.fresh()
    model.train(x[~held], y[~held])
    model.calibrate(x[held], y[held], binding=new[held])
    return model


def find_secrets(docs: DataFrame, model: CharCNN | None = None, text: str = "text") -> DataFrame:
    """docs with secrets: array of (kind, start, end, score) by start, then kind; code points, end exclusive.

    Base spans always stay; kind model marks what the network adds at or over its threshold.
    """
    held = docs.sparkSession.sparkContext.broadcast(model if model is not None else train_model(docs, text))
    docs = docs.drop("secrets")
    if text not in docs.columns:
        docs = docs.withColumn(text, F.lit(None).cast("string"))
    at = docs.columns.index(text)
    schema = pa.schema([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())])

    def scan(batches):
        cnn = held.value
        for batch in batches:
            spans, coded, where, first = [], [], [], []
            for i, t in enumerate(batch.column(at).to_pylist()):
                base = base_spans(t := t or "")
                for s, e, k in base:
                    spans.append([i, s, k, e, KINDS[k]])
                for s, e in other_candidates(t, base):
                    spans.append([i, s, len(KINDS), e, MODEL_KIND])
                for x in spans[len(where) :]:
                    first.append(len(coded))
                    coded += [encode(t, a, z) for a, z in views(x[1], x[3])]
                    where.append(x)
            score = np.maximum.reduceat(cnn.score(np.stack(coded)), first) if coded else np.empty(0)
            kept = sorted((*x, p) for x, p in zip(spans, score.tolist(), strict=True) if x[2] < len(KINDS) or p >= cnn.threshold)
            ends = np.searchsorted([x[0] for x in kept], np.arange(batch.num_rows + 1))
            values = pa.StructArray.from_arrays([pa.array([x[4] for x in kept], pa.string()), pa.array([x[1] for x in kept], pa.int32()), pa.array([x[3] for x in kept], pa.int32()), pa.array([x[5] for x in kept], pa.float64())], fields=list(schema))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.ListArray.from_arrays(pa.array(ends, pa.int32()), values)], [*batch.schema.names, "secrets"])

    from pyspark.sql.types import StructType

    return docs.mapInArrow(scan, StructType([*docs.schema.fields, *StructType.fromDDL(f"secrets {SPAN}").fields]))


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = docs.sparkSession.sparkContext.broadcast(train_model(docs))
    none = hashlib.sha256(b"").hexdigest()

    def digest(batches):
        for batch in batches:
            out = []
            for got in batch.column(1).to_pylist():
                listed = [f"{x['kind']}:{x['start']}:{x['end']}" for x in got]
                base = [s for s in listed if not s.startswith(MODEL_KIND)]
                n = [sum(s.startswith(k) for s in base) for k in KINDS]
                out.append((*n, hashlib.sha256(",".join(base).encode()).hexdigest() if base else none, ",".join(listed)))
            cols = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in cols[:3]), *(pa.array(c, pa.string()) for c in cols[3:])], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    found = find_secrets(docs, model.value).select("doc_id", "secrets")
    return found.mapInArrow(digest, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
