"""Answer heads over the states of a stack: is there an answer, which paragraph, which words; fitted by gradient."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np


ANSWER_WORDS = 3
FEATURES = 5


@dataclass(frozen=True)
class Knobs:
    """Of a fit.  Updates first warm up to the full rate, then fall to nothing."""

    rate: float = 0.05
    updates: int = 600
    warm_up: int = 60  # a tenth
    batch: int = 160
    clip: float = 1.0
    dropout: float = 0.1
    seed: int = 0

    def rate_at(self, step: int) -> float:
        if step < self.warm_up:
            return self.rate * (step + 1) / self.warm_up
        return self.rate * max(0.0, (self.updates - step) / max(1, self.updates - self.warm_up))


#: As published, for questions: what a fit of the whole encoder would use.
PUBLISHED_QA = Knobs(rate=5e-5, updates=22_200, warm_up=2_220, batch=160, clip=np.inf, dropout=0.1)
#: The rates of dropout that are tried, the best on validation questions is kept.
DROPOUTS = (0.1, 0.15, 0.2)


def fit_logistic(x: np.ndarray, y: np.ndarray, knobs: Knobs, init: np.ndarray | None = None) -> np.ndarray:
    """Weights of a logistic regression by Adam; the rarer label counts as much; init: where a second phase starts."""
    g, w = np.random.default_rng(knobs.seed), np.zeros(x.shape[1]) if init is None else init.copy()
    if not len(y) or y.min() == y.max():
        return w
    descent = Descent(w, float(y.mean()), knobs, g)
    for step in range(knobs.updates):
        at = g.integers(0, len(y), min(knobs.batch, len(y)))
        descent.see(x[at], y[at])
        descent.update(step)
    return descent.w


class Descent:
    """One fit on its way: rows are seen, any number at a time, and each update uses what was seen since the last."""

    def __init__(self, w: np.ndarray, share: float, knobs: Knobs, g: np.random.Generator):
        self.w, self.share, self.knobs, self.g = w, share, knobs, g
        self.mean, self.var = np.zeros_like(w), np.zeros_like(w)
        self.grad, self.n = np.zeros_like(w), 0

    def see(self, x: np.ndarray, y: np.ndarray) -> None:
        keep = (self.g.random(x.shape) >= self.knobs.dropout) / (1 - self.knobs.dropout)
        keep[:, 0] = 1  # the constant
        v = x * keep
        p = 1 / (1 + np.exp(-np.clip(v @ self.w, -30, 30)))
        self.grad = self.grad + v.T @ (np.where(y > 0, 0.5 / self.share, 0.5 / (1 - self.share)) * (p - y))
        self.n += len(y)

    def update(self, step: int) -> None:
        if not self.n:
            return
        grad = self.grad / self.n
        norm = np.linalg.norm(grad)
        if norm > self.knobs.clip:
            grad *= self.knobs.clip / norm
        self.mean += 0.1 * (grad - self.mean)
        self.var += 0.001 * (grad * grad - self.var)
        self.w -= self.knobs.rate_at(step) * (self.mean / (1 - 0.9 ** (step + 1))) / (np.sqrt(self.var / (1 - 0.999 ** (step + 1))) + 1e-8)
        self.grad, self.n = np.zeros_like(self.w), 0


def passes(n: int, knobs: Knobs) -> int:
    """How often each of n rows is seen where rows are dealt to the updates and not drawn: once, or more where few."""
    return max(1, min(knobs.updates, knobs.batch * knobs.updates // max(1, n)))


@dataclass
class Read:
    """What the heads see of one question: features and read words of each paragraph, and the pooled first states."""

    feats: np.ndarray  # paragraphs by FEATURES
    words: list[str]
    pooled: np.ndarray


def read(plan, q: list[str], paras: list[list[str]], states_of) -> Read:
    """One pass of the stack over the question and all paragraphs, a sentinel before each."""
    return read_all([plan], q, paras, states_of)[0]


def read_all(plans: list, q: list[str], paras: list[list[str]], states_of, depth: int = 1) -> list[Read]:
    """The same under each plan; the layers below depth (their common_depth) run once."""
    from longweave.plans.stack import encode_all

    toks, spans = [], []
    for p in paras:
        spans.append((len(toks), len(toks) + 1 + len(p)))
        toks += ["<s>", *p]
    return [_seen(len(q), toks, spans, ctx, qs) for ctx, qs in encode_all(plans, states_of(toks), states_of(q), depth)]


def read_several(plans: list, asked: list[tuple[list[str], list[list[str]]]], states_of, depth: int = 1) -> list[list[Read]]:
    """read_all of each (question, paragraphs); those whose questions are of equal length go through the layers together."""
    from longweave.plans.stack import encode_all_several

    out: list = [None] * len(asked)
    toks, spans = [[] for _ in asked], [[] for _ in asked]
    by: dict[int, list[int]] = {}
    for i, (q, paras) in enumerate(asked):
        for p in paras:
            spans[i].append((len(toks[i]), len(toks[i]) + 1 + len(p)))
            toks[i] += ["<s>", *p]
        by.setdefault(len(q) if all(p.stride == plans[0].stride for p in plans) else -1 - i, []).append(i)
    for own in by.values():
        got = encode_all_several(plans, [states_of(toks[i]) for i in own], [states_of(asked[i][0]) for i in own], depth)
        for i, each in zip(own, got, strict=True):
            out[i] = [_seen(len(asked[i][0]), toks[i], spans[i], ctx, qs) for ctx, qs in each]
    return out


def _seen(n: int, toks: list[str], spans: list[tuple[int, int]], ctx: np.ndarray, qs: np.ndarray) -> Read:
    unit = lambda h: h / np.maximum(np.linalg.norm(h, axis=-1, keepdims=True), 1e-9)
    near = unit(ctx) @ unit(qs.mean(0)).T  # rows of the context by those of the question
    feats, words, at_once = [], [], np.arange(n)
    along = near[np.arange(max(0, len(near) - n + 1))[:, None] + at_once, at_once].mean(1)  # of the question laid on from each row
    for lo, hi in spans:
        top, own = near[lo:hi].max(0), along[lo : max(lo, hi - n + 1)]
        at = int(own.argmax()) if len(own) else 0
        feats.append([1.0, top.mean(), top.min(), own[at] if len(own) else top.mean() - 1, near[lo].mean()])
        words.append(" ".join(toks[lo + at + n : min(hi, lo + at + n + ANSWER_WORDS)]))
    return Read(np.array(feats).reshape(-1, FEATURES), words, qs[:, 0].mean(0))


@dataclass
class Heads:
    """Paragraph head over its features; answer head over the best paragraph's features, its lead and the pooled state."""

    para: np.ndarray
    answer: np.ndarray
    threshold: float = 0.5
    dropout: float = 0.0
    dev: dict = field(default_factory=dict)

    def scores(self, feats: np.ndarray, pooled: np.ndarray) -> tuple[np.ndarray, float]:
        """(score of each paragraph, probability that there is an answer)."""
        s = feats @ self.para
        return s, float(1 / (1 + np.exp(-np.clip(answer_input(feats, pooled, s) @ self.answer, -30, 30))))


def answer_input(feats: np.ndarray, pooled: np.ndarray, s: np.ndarray) -> np.ndarray:
    best = feats[int(s.argmax())]
    return np.concatenate([best, pooled])


def f1(pairs: list[tuple]) -> float:
    """Of (predicted, right), None for no answer."""
    tp = sum(p is not None and p == g for p, g in pairs)
    wrong = sum(p is not None and p != g for p, g in pairs)
    missed = sum(p is None and g is not None for p, g in pairs)
    return 2 * tp / max(1, 2 * tp + wrong + missed)


def fit_heads(rows: list[dict], knobs: Knobs, init: Heads | None = None, dropouts=DROPOUTS) -> Heads:
    """rows: feats, pooled, gold (number of a paragraph or None) and dev (judge, don't fit).  The rate of dropout with the
    best F1 of paragraphs on the rows to judge by is kept."""
    fit = [r for r in rows if not r["dev"]] or rows
    dev = [r for r in rows if r["dev"]] or rows
    best, tried = None, {}
    for rate in dropouts:
        k = replace(knobs, dropout=rate)
        some = [r for r in fit if r["gold"] is not None and len(r["feats"])]
        x = np.concatenate([r["feats"] for r in some]) if some else np.zeros((0, FEATURES))
        y = np.concatenate([np.arange(len(r["feats"])) == r["gold"] for r in some]).astype(float) if some else np.zeros(0)
        para = fit_logistic(x, y, k, init.para if init else None)
        held = [r for r in fit if len(r["feats"])]
        z = np.array([answer_input(r["feats"], r["pooled"], r["feats"] @ para) for r in held])
        ans = fit_logistic(z, np.array([r["gold"] is not None for r in held], float), k, init.answer if init else None) if held else np.zeros(FEATURES + 1)
        h = Heads(para, ans, 0.5, rate)
        tried[rate] = f1([(answered(h, r["feats"], r["pooled"]), r["gold"]) for r in dev if len(r["feats"])])
        if best is None or tried[rate] > tried[best.dropout]:
            best = h
    best.dev = tried
    return best


def answered(heads: Heads | list[Heads], feats: np.ndarray, pooled: np.ndarray | list[np.ndarray]) -> int | None:
    """Number of the chosen paragraph, or None.  Of several models (feats and pooled: one each) scores are averaged."""
    if isinstance(heads, Heads):
        heads, feats, pooled = [heads], [feats], [pooled]
    s = [h.scores(f, p) for h, f, p in zip(heads, feats, pooled, strict=True)]
    total = np.mean([shares(x) for x, _ in s], 0)
    return int(total.argmax()) if np.mean([p for _, p in s]) >= np.mean([h.threshold for h in heads]) else None


def shares(x: np.ndarray) -> np.ndarray:
    """Scores of one question on a common scale."""
    e = np.exp(x - x.max())
    return e / e.sum()
