"""Dense kernels over one sequence (NumPy only).  A sequence is a matrix of states, one row per token.

Windows are [stride k, min(x, stride k + win)) for k below ceil(x / stride), each with all question rows in front.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass

import numpy as np

try:  # Python's own is quicker on short texts than the library behind hashlib
    from _md5 import md5
except ImportError:
    from hashlib import md5

Encode = Callable[[np.ndarray], np.ndarray]


# ---------------------------------------------------------------- states
def token_vector(tok: str, d: int, seed: int) -> np.ndarray:
    """Integer coordinates in [-8, 8]: dot products are exact in double precision."""
    return token_vectors([tok], d, seed)[0]


def token_vectors(toks: list[str], d: int, seed: int) -> np.ndarray:
    """token_vector of each."""
    ends = [f":{j}:{seed}".encode() for j in range(d)]
    heads = b"".join([md5(tok + end).digest()[:4] for tok in (t.encode() for t in toks) for end in ends])
    return (np.frombuffer(heads, ">u4") % 17 - 8.0).reshape(len(toks), d)


class TokenVectors:
    """Vectors by token, computed once per worker and token; bounded."""

    most = 400_000

    def __init__(self, d: int = 8, seed: int = 7):
        self.d, self.seed, self.known, self.rows = d, seed, {}, np.empty((0, d))

    def __call__(self, toks: Iterable[str]) -> np.ndarray:
        if len(self.known) > self.most:
            self.known.clear()
        at, new, had = [], [], len(self.known)
        for t in toks:
            i = self.known.get(t)
            if i is None:
                i = self.known[t] = had + len(new)
                new.append(t)
            at.append(i)
        if had + len(new) > len(self.rows):
            self.rows = np.concatenate([self.rows[:had], np.empty((had + 2 * len(new), self.d))])
        if new:
            self.rows[had : had + len(new)] = token_vectors(new, self.d, self.seed)
        return self.rows[np.array(at, int)]


def position_codes(rows: int, d: int) -> np.ndarray:
    """Sine and cosine codes of a row within its window; the same table serves every window."""
    angle = np.arange(rows)[:, None] / 10000 ** (2 * (np.arange(d) // 2) / d)
    return np.where(np.arange(d) % 2 == 0, np.sin(angle), np.cos(angle))


# ---------------------------------------------------------------- attention
def attention(h: np.ndarray, keys: np.ndarray | None = None, scale: float | None = None, mask: np.ndarray | None = None) -> np.ndarray:
    """Softmax of scaled dot products, identity projections; axes before the last two are a batch.  mask[i, j]: row i may
    read row j."""
    if keys is h and h.ndim == 2 and mask is None:
        return _among_all(h, 1 / np.sqrt(h.shape[-1]) if scale is None else scale)
    keys = h if keys is None else keys
    s = h @ keys.swapaxes(-1, -2) * (1 / np.sqrt(h.shape[-1]) if scale is None else scale)
    if mask is not None:
        s = np.where(mask, s, -np.inf)
    s = np.exp(s - s.max(-1, keepdims=True))
    return (s / s.sum(-1, keepdims=True)) @ keys


def _among_all(x: np.ndarray, scale: float) -> np.ndarray:
    """Every row reads all, a bounded number of rows at a time.  Scores are the same both ways, so an exponential serves two
    rows where it needs no shift."""
    n, lo = len(x), 0
    if not float(np.einsum("ij,ij->i", x, x).max(initial=0)) * abs(scale) < SAFE:
        step = max(1, 4_000_000 // n)
        return np.concatenate([attention(x[at : at + step], x[:], scale) for at in range(0, n, step)])
    ones, y = np.concatenate([x, np.ones((n, 1))], 1), np.ascontiguousarray(x.T) * scale
    total = np.zeros_like(ones)
    while lo < n:
        hi = min(n, lo + max(32, AT_ONCE // (n - lo)))
        s = x[lo:hi] @ y[:, lo:]
        np.exp(s, out=s)
        total[lo:hi] += s @ ones[lo:]
        total[hi:] += s[:, hi - lo :].T @ ones[lo:hi]
        lo = hi
    return total[:, :-1] / total[:, -1:]


@dataclass
class Block:
    """A seeded transformer block: pre-norm multi-head attention and feed-forward, both residual; axes before the last two
    are a batch.  drop: share of what each branch adds that is left out, the rest scaled up (training only)."""

    wq: np.ndarray
    wk: np.ndarray
    wv: np.ndarray
    wo: np.ndarray
    w1: np.ndarray
    w2: np.ndarray
    heads: int = 2
    eps: float = 1e-5
    drop: float = 0.0
    gain: np.ndarray | float = 1.0  # learned scale and shift after each norm
    shift: np.ndarray | float = 0.0

    @classmethod
    def seeded(cls, d: int, heads: int = 2, d_ff: int | None = None, seed: int = 0) -> Block:
        g, f = np.random.default_rng(seed), d_ff or 4 * d
        return cls(*(g.normal(0, d**-0.5, (d, d)) for _ in range(4)), g.normal(0, d**-0.5, (d, f)), g.normal(0, f**-0.5, (f, d)), heads)

    def norm(self, x: np.ndarray) -> np.ndarray:
        mean = np.full(x.shape[-1], 1 / x.shape[-1])  # products with it are sums along a short axis
        x = x - (x @ mean)[..., None]
        return x / np.sqrt((x * x) @ mean + self.eps)[..., None] * self.gain + self.shift

    def __call__(self, h: np.ndarray, mask: np.ndarray | None = None, rng: np.random.Generator | None = None, held: np.ndarray | None = None) -> np.ndarray:
        """held: rows from there on, a number for each of the batch, are there to fill it up; none is read."""
        if mask is None and h.ndim == 3 and not (rng is not None and self.drop):
            return self._by_columns(h, held)
        *lead, n, d = h.shape
        kept = lambda x: x * (rng.random(x.shape) >= self.drop) / (1 - self.drop) if rng is not None and self.drop else x
        x = self.norm(h).reshape(-1, d)
        q, k, v = ((x @ w).reshape(-1, n, self.heads, d // self.heads).swapaxes(-2, -3) for w in (self.wq / np.sqrt(d // self.heads), self.wk, self.wv))
        if mask is not None and mask.ndim > 2:
            mask = np.broadcast_to(mask, (*lead, n, n)).reshape(-1, n, n)
        h = h + kept(soft_read(q, k, v, mask, held).swapaxes(-2, -3).reshape(*lead, n, d) @ self.wo)
        return h + kept(np.maximum(self.norm(h).reshape(-1, d) @ self.w1, 0).reshape(*lead, n, -1) @ self.w2)

    def _norm_columns(self, x: np.ndarray) -> np.ndarray:
        mean = np.full(len(x), 1 / len(x))
        x = x - mean @ x
        x *= 1 / np.sqrt(mean @ (x * x) + self.eps)
        plain = all(isinstance(w, float) for w in (self.gain, self.shift)) and (self.gain, self.shift) == (1.0, 0.0)
        return x if plain else x * np.reshape(self.gain, (-1, 1)) + np.reshape(self.shift, (-1, 1))

    def _largest(self) -> float:
        """No score is larger: rows after the norm are no longer than the root of their coordinates."""
        d, own = len(self.wq), len(self.wq) // self.heads
        row = d * (np.abs(self.gain).max() + np.abs(self.shift).max()) ** 2
        squares = [(w * w).reshape(d, self.heads, own).sum((0, 2)) for w in (self.wq, self.wk)]
        return float(row * np.sqrt(squares[0] * squares[1] / own).max())

    def _by_columns(self, h: np.ndarray, held: np.ndarray | None) -> np.ndarray:
        """Every row of a batch reads its others: the same with a column for each row, so that all steps run along long axes."""
        b, n, d = h.shape
        own = d // self.heads
        x = np.ascontiguousarray(h.reshape(-1, d).T, dtype=np.float64)
        last = np.concatenate([self.wv.T.reshape(self.heads, own, d), np.zeros((self.heads, 1, d))], 1).reshape(-1, d)  # room for ones
        made = np.concatenate([self.wq.T / np.sqrt(own), self.wk.T, last]) @ self._norm_columns(x)
        q, k = (made[at : at + d].reshape(self.heads, own, b, n).transpose(2, 0, 1, 3) for at in (0, d))
        v = made[2 * d :].reshape(self.heads, own + 1, b, n)
        v[:, own] = 1  # counts the keys
        if held is not None:
            v *= np.arange(n) < held[:, None]
        k, v, safe = k.swapaxes(-1, -2), v.transpose(2, 0, 1, 3), self._largest() < SAFE
        got = np.empty((d, b * n))
        out = got.reshape(self.heads, own, b, n).transpose(2, 0, 1, 3)
        rows = min(n, max(32, AT_ONCE // max(1, self.heads * n)))
        step = max(1, AT_ONCE // max(1, self.heads * n * rows))
        room = np.empty(min(step, b) * self.heads * n * rows)
        for at in range(0, b, step):
            z = min(b, at + step)
            for lo in range(0, n, max(1, rows)):
                hi = min(n, lo + rows)
                s = room[: (z - at) * self.heads * n * (hi - lo)].reshape(z - at, self.heads, n, hi - lo)  # keys by rows
                np.matmul(k[at:z], q[at:z, ..., lo:hi], out=s)
                if not safe:
                    if held is not None:
                        np.copyto(s, -np.inf, where=(np.arange(n) >= held[at:z, None])[:, None, :, None])
                    s -= s.max(-2, keepdims=True)
                np.exp(s, out=s)
                both = v[at:z] @ s
                np.divide(both[:, :, :own], both[:, :, own:], out=out[at:z, ..., lo:hi])
        x += self.wo.T @ got
        wide = self.w1.T @ self._norm_columns(x)
        np.maximum(wide, 0.0, out=wide)
        x += self.w2.T @ wide
        return np.ascontiguousarray(x.T).reshape(h.shape)


#: Scores up to this have exponentials, and sums of them, that double precision holds without a shift by the largest.
SAFE = 500.0
#: Scores at a time: what a core's cache holds.
AT_ONCE = 1 << 16


def soft_read(q: np.ndarray, k: np.ndarray, v: np.ndarray, mask: np.ndarray | None = None, held: np.ndarray | None = None) -> np.ndarray:
    """Softmax(q k) v of batches by heads by rows by coordinates; mask: rows by rows, for all or one for each of the batch;
    held: of each of the batch, so many keys count.

    A part of the batch and of the rows at a time; keys that no row of a part may read are left out.
    """
    (b, heads, n, d), m = q.shape, k.shape[2]
    out = np.empty((b, heads, n, v.shape[-1]))
    longest = lambda x: np.sqrt(np.einsum("...i,...i->...", x, x).max(initial=0))
    safe = longest(q) * longest(k) < SAFE
    q, k = np.ascontiguousarray(q), np.ascontiguousarray(k.swapaxes(-1, -2))
    v = np.concatenate([v, np.ones((b, heads, m, 1))], -1)
    if held is not None:
        v *= (np.arange(m) < held[:, None])[:, None, :, None]  # the last coordinate counts the keys
    rows = min(n, max(32, AT_ONCE // max(1, heads * m)))
    step, room = max(1, AT_ONCE // max(1, heads * m * rows)), None
    for lo in range(0, n, max(1, rows)):
        hi, own, upto, since = min(n, lo + rows), None, m, 0
        if mask is not None:
            own = mask[..., lo:hi, :]
            seen = own.reshape(-1, m)
            upto = m - int(seen.any(0)[::-1].argmax()) if m else 0
            since = int((~seen.all(0)).argmax()) if not seen.all() else upto
        for at in range(0, b, step):
            z = min(b, at + step)
            shape = (z - at, heads, hi - lo, upto)
            size = int(np.prod(shape))
            room = np.empty(size) if room is None or len(room) < size else room
            s = np.matmul(q[at:z, :, lo:hi], k[at:z, :, :, :upto], out=room[:size].reshape(shape))
            bar = own if own is None or own.ndim == 2 else own[at:z, None]
            if not safe:
                if bar is not None:
                    np.copyto(s, -np.inf, where=~bar[..., :upto])
                if held is not None:
                    np.copyto(s, -np.inf, where=(np.arange(upto) >= held[at:z, None])[:, None, None])
                s -= s.max(-1, keepdims=True)
            np.exp(s, out=s)
            if bar is not None and safe and since < upto:
                s[..., since:] *= bar[..., since:upto]
            got = s @ v[at:z, :, :upto]
            np.divide(got[..., :-1], got[..., -1:], out=out[at:z, :, lo:hi])
    return out


# ---------------------------------------------------------------- windows
def check_window(win: int, stride: int) -> None:
    if not 0 < stride < win:
        raise ValueError(f"stride {stride} must be positive and below the window's {win} rows")


def window_bounds(x: int, win: int, stride: int) -> list[tuple[int, int]]:
    check_window(win, stride)
    return [(lo, min(x, lo + win)) for lo in range(0, x, stride)]


def slice_windows(x: np.ndarray, q: np.ndarray, win: int, stride: int) -> list[np.ndarray]:
    return [np.concatenate([q, x[lo:hi]]) for lo, hi in window_bounds(len(x), win, stride)]


#: Lengths of windows and blocks of several sequences are filled up to a multiple of this, by copies of their last row.
FILL = 24
#: Coordinates of several sequences' states at a time: what a core's cache holds with all that a layer makes of them.
AT_A_TIME = 24_000


def filled(rows: list[np.ndarray]) -> Iterable[tuple[np.ndarray, np.ndarray]]:
    """rows (numbers, at least one each), those of near lengths as one matrix: (matrix, how many of each line are its own)."""
    by: dict[int, list[np.ndarray]] = {}
    for r in rows:
        by.setdefault(-(-len(r) // FILL) * FILL, []).append(r)
    for group in by.values():
        held = np.array([len(r) for r in group])
        at = np.minimum(np.arange(held.max()), held[:, None] - 1) + (np.cumsum(held) - held)[:, None]
        yield np.concatenate(group)[at], held


def encode_several(ctx: np.ndarray, qs: np.ndarray, sizes: list[int], win: int, stride: int, encode: Callable, codes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """encode_merged of several sequences, one after the other in ctx and qs; sizes: their rows.  encode(h, held=...)."""
    (x, d), n_q = ctx.shape, qs.shape[1]
    starts = np.cumsum([0, *sizes])
    bounds = np.array([(a + lo, a + hi) for a, n in zip(starts.tolist(), sizes, strict=False) for lo, hi in window_bounds(n, win, stride)]).reshape(-1, 2)
    total, out_q = np.zeros((x, d)), np.empty_like(qs, dtype=np.float64)
    count = np.cumsum(np.bincount(bounds[:, 0], minlength=x + 1) - np.bincount(bounds[:, 1], minlength=x + 1))[:x]
    size = bounds[:, 1] - bounds[:, 0]
    of = -(-size // FILL)
    for length in np.unique(of):
        own = np.flatnonzero(of == length)
        length = int(size[own].max())
        step = max(1, AT_A_TIME // ((n_q + length) * d))
        for k in (own[i : i + step] for i in range(0, len(own), step)):
            h, held, spans = np.empty((len(k), n_q + length, d)), n_q + size[k], bounds[k].tolist()
            h[:, :n_q] = qs[k]
            for to, (lo, hi) in zip(h, spans, strict=True):  # a window's rows lie together
                to[n_q : n_q + hi - lo] = ctx[lo:hi]
                to[n_q + hi - lo :] = ctx[hi - 1]
            if codes is not None:
                h += codes[: n_q + length]
            h = encode(h, held=None if (held == n_q + length).all() else held)
            out_q[k] = h[:, :n_q]
            for own_rows, (lo, hi) in zip(h, spans, strict=True):
                total[lo:hi] += own_rows[n_q : n_q + hi - lo]
    return total / count[:, None], out_q


def encode_merged(ctx: np.ndarray, qs: np.ndarray, win: int, stride: int, encode: Callable, codes: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """One window layer over merged states: (context, question rows of each window) after encoding and merging.

    ctx: x by d; qs: windows by question rows by d.  Windows of equal length are encoded together.
    """
    x, d = ctx.shape
    n_q = qs.shape[1]
    bounds = np.array(window_bounds(x, win, stride)).reshape(-1, 2)
    total, count, out_q = np.zeros((x, d)), np.zeros(x), np.empty_like(qs, dtype=np.float64)
    size, apart = bounds[:, 1] - bounds[:, 0], -(-win // stride)  # so many windows on, none overlaps
    for length in np.unique(size):
        own = np.flatnonzero(size == length)
        step = max(1, 1_000_000 // ((n_q + length) * d))
        for k in (own[i : i + step] for i in range(0, len(own), step)):
            at = bounds[k, :1] + np.arange(length)
            h = np.concatenate([qs[k], ctx[at]], 1)
            h = encode(h if codes is None else h + codes[: n_q + length])
            out_q[k] = h[:, :n_q]
            for first in range(min(apart, len(k))):
                total[at[first::apart]] += h[first::apart, n_q:]
                count[at[first::apart]] += 1
    return total / count[:, None], out_q


def merge_overlaps(windows: list[np.ndarray], n_q: int, x: int, win: int, stride: int) -> list[np.ndarray]:
    """Context rows that several windows hold become the mean of all their encodings, in each of these windows."""
    bounds = window_bounds(x, win, stride)
    if not bounds:
        return []
    total, n = np.zeros((x, windows[0].shape[1])), np.zeros(x)
    for (lo, hi), h in zip(bounds, windows, strict=True):
        total[lo:hi] += h[n_q:]
        n[lo:hi] += 1
    mean = total / n[:, None]
    return [np.concatenate([h[:n_q], mean[lo:hi]]) for (lo, hi), h in zip(bounds, windows, strict=True)]


def dedup_concat(windows: list[np.ndarray], n_q: int, stride: int) -> np.ndarray:
    return np.concatenate([h[: n_q + stride] for h in windows]) if windows else np.empty((0, 0))


def rewindow(states: np.ndarray, n_q: int, x: int, win: int, stride: int) -> list[np.ndarray]:
    """Windows again from the de-duplicated list; each gets its own copy of the question back."""
    step, out = n_q + stride, []
    context = np.concatenate([states[k : k + step][n_q:] for k in range(0, len(states), step)]) if len(states) else states
    for k, (lo, hi) in enumerate(window_bounds(x, win, stride)):
        out.append(np.concatenate([states[k * step : k * step + n_q], context[lo:hi]]))
    return out


# ---------------------------------------------------------------- clusters
def similarity(states: np.ndarray, centroids: np.ndarray, metric: str = "cosine") -> np.ndarray:
    """The larger the nearer; a zero vector has cosine 0 to all."""
    s = states @ centroids.T
    if metric == "dot":
        return s
    if metric == "l2":
        return 2 * s - (states**2).sum(1)[:, None] - (centroids**2).sum(1)
    norm = np.sqrt((states**2).sum(1))[:, None] * np.sqrt((centroids**2).sum(1))
    return np.divide(s, norm, out=np.zeros_like(s), where=norm > 0)


#: From so many centroids on, nearest ones are looked for in single precision first.
MANY = 64


def assign(states: np.ndarray, centroids: np.ndarray, metric: str = "cosine") -> np.ndarray:
    step = max(1, 100_000 // max(1, len(centroids)))  # so many similarities as a cache holds
    nearest = _nearest_cosine(centroids) if metric == "cosine" and len(centroids) >= MANY else lambda x: similarity(x, centroids, metric).argmax(1)
    parts = [nearest(states[i : i + step]) for i in range(0, len(states), step)]  # the first of equals
    return np.concatenate(parts) if parts else np.empty(0, np.int64)


def _nearest_cosine(centroids: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """similarity(states, centroids).argmax(1), by products in single precision; where the best two are nearer than those
    can tell, in double precision."""
    unit = lambda x: np.nan_to_num(x / np.maximum(np.sqrt((x * x).sum(1)), 1e-150)[:, None]).astype(np.float32)
    far, apart = np.ascontiguousarray(unit(centroids).T), (centroids.shape[1] + 8) * 2.0**-22

    def nearest(x: np.ndarray) -> np.ndarray:
        s, rows = unit(x) @ far, np.arange(len(x))
        out = s.argmax(1)
        top = s[rows, out]
        s[rows, out] = -np.inf
        unsure = np.flatnonzero(~(top - s.max(1) > apart))
        if len(unsure):
            out[unsure] = similarity(x[unsure], centroids).argmax(1)
        return out

    return nearest


def chain_order(centroids: np.ndarray, start: int = 0) -> list[int]:
    """Greedy walk: from start, always to the most cosine-similar centroid not yet visited (ties: smaller index)."""
    sim = similarity(centroids, centroids)
    left, out = set(range(len(centroids))) - {start}, [start]
    while left:
        out.append(max(left, key=lambda c: (sim[out[-1], c], -c)))
        left.remove(out[-1])
    return out


def blocks_of(labels: np.ndarray, stride: int, layout: str = "uniform") -> list[np.ndarray]:
    """Row numbers of each block: uniform cuts ignore cluster borders; strict ones start anew at each border; padded
    ones hold a whole cluster each."""
    order = np.argsort(labels, kind="stable")
    if layout in ("uniform", "masked"):
        return [order[i : i + stride] for i in range(0, len(order), stride)]
    groups = np.split(order, np.flatnonzero(np.diff(labels[order])) + 1) if len(order) else []
    return groups if layout == "padded" else [g[i : i + stride] for g in groups for i in range(0, len(g), stride)]


def cluster_attention(states: np.ndarray, labels: np.ndarray, stride: int, encode=attention, layout: str = "uniform", causal: np.ndarray | None = None) -> np.ndarray:
    """Attention inside each block, rows back in their own order.  causal: a time per row; rows read no later ones."""
    return attend_blocks(states, blocks_of(labels, stride, layout), encode, labels if layout == "masked" else None, causal)


def attend_blocks(states: np.ndarray, blocks: list[np.ndarray], encode=attention, labels: np.ndarray | None = None, causal: np.ndarray | None = None) -> np.ndarray:
    """Attention inside each of the blocks of rows; blocks of equal length together.  labels: rows read equal ones only."""
    out = np.empty_like(states)
    by: dict[int, list[np.ndarray]] = {}
    for rows in blocks:
        by.setdefault(len(rows), []).append(rows)
    for length, group in by.items():
        step = max(1, 4_000_000 // length**2)
        for at in range(0, len(group), step):
            rows, mask = np.stack(group[at : at + step]), None
            if labels is not None:
                mask = labels[rows][:, :, None] == labels[rows][:, None]
            if causal is not None:
                past = causal[rows][:, :, None] >= causal[rows][:, None]
                mask = past if mask is None else mask & past
            out[rows] = encode(states[rows], mask=mask) if mask is not None else encode(states[rows])
    return out


def attend_several(states: np.ndarray, blocks: list[np.ndarray], encode: Callable, causal: bool = False) -> np.ndarray:
    """attend_blocks of blocks that may be those of several sequences; causal: rows read no later ones.  encode(h, held=...)."""
    out = np.empty_like(states)
    for rows, held in filled(blocks):
        step = max(1, AT_A_TIME // (rows.shape[1] * states.shape[1]))
        for k in (slice(at, at + step) for at in range(0, len(rows), step)):
            mask = rows[k, :, None] >= rows[k, None] if causal else None
            own = np.arange(rows.shape[1]) < held[k, None]
            if own.all():
                out[rows[k]] = encode(states.take(rows[k], 0), mask, held=None)
            else:
                out[rows[k][own]] = encode(states.take(rows[k], 0), mask, held=held[k])[own]
    return out


def lloyd_step(bank: np.ndarray, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(labels, new centroids); an empty cluster keeps its centroid."""
    labels = assign(bank, centroids, "l2")
    n = np.bincount(labels, minlength=len(centroids))
    total = np.stack([np.bincount(labels, bank[:, j], len(centroids)) for j in range(bank.shape[1])], 1)
    return labels, np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], centroids)


def kmeans(bank: np.ndarray, init: np.ndarray, iters: int = 20, tol: float = 0.0) -> tuple[np.ndarray, np.ndarray, int]:
    """Lloyd: (centroids, labels, distance evaluations)."""
    c, n = init.copy(), 0
    for _ in range(iters):
        _, new = lloyd_step(bank, c)
        n += len(bank) * len(c)
        moved = np.abs(new - c).max() if len(c) else 0
        c = new
        if moved <= tol:
            break
    return c, assign(bank, c, "l2"), n


def kmeans_bounded(bank: np.ndarray, init: np.ndarray, iters: int = 20, tol: float = 0.0) -> tuple[np.ndarray, np.ndarray, int]:
    """The same result as Lloyd from the same start; an upper bound to the own centroid and one lower bound per group of
    centroids (about ten each) save distance evaluations."""
    c, k = init.copy(), len(init)
    groups = max(1, k // 10)
    of = kmeans(init, init[:groups], 5)[1] if groups > 1 else np.zeros(k, dtype=int)
    dist = lambda rows, cols: np.sqrt(np.maximum(((bank[rows][:, None] - c[cols][None]) ** 2).sum(2), 0))
    full = dist(slice(None), slice(None))
    n = full.size
    label, rows = full.argmin(1), np.arange(len(bank))
    upper = full[rows, label]
    full[rows, label] = np.inf
    lower = np.stack([full[:, of == g].min(1) if (of == g).any() else np.full(len(bank), np.inf) for g in range(groups)], 1)
    for _ in range(iters):
        count = np.bincount(label, minlength=k)
        total = np.zeros_like(c)
        np.add.at(total, label, bank)
        new = np.where(count[:, None] > 0, total / np.maximum(count, 1)[:, None], c)
        drift = np.sqrt(((new - c) ** 2).sum(1))
        c = new
        upper += drift[label]
        lower -= np.array([drift[of == g].max() if (of == g).any() else 0 for g in range(groups)])
        if np.abs(drift).max() <= tol:
            break
        check = np.flatnonzero(upper >= lower.min(1) - 1e-12)
        if len(check):
            upper[check] = np.sqrt(((bank[check] - c[label[check]]) ** 2).sum(1))
            n += len(check)
            check = check[upper[check] >= lower[check].min(1) - 1e-12]
        best, best_label = upper[check].copy(), label[check].copy()
        tested: list[tuple] = []
        for g in range(groups):
            cols = np.flatnonzero(of == g)
            open_ = np.flatnonzero(best >= lower[check, g] - 1e-12)
            if not len(open_) or not len(cols):
                continue
            d = dist(check[open_], cols)
            n += d.size
            tested.append((g, cols, open_, d))
            for j, col in enumerate(cols):
                near = (d[:, j] < best[open_]) | ((d[:, j] == best[open_]) & (col < best_label[open_]))
                at = open_[near]
                best[at], best_label[at] = d[near, j], col
        for g, cols, open_, d in tested:
            lower[check[open_], g] = np.where(best_label[open_][:, None] == cols, np.inf, d).min(1)
        moved = best_label != label[check]
        for i in np.flatnonzero(moved):  # the centroid left behind bounds its group from now on
            g = of[label[check[i]]]
            lower[check[i], g] = min(lower[check[i], g], np.sqrt(((bank[check[i]] - c[label[check[i]]]) ** 2).sum()))
        n += int(moved.sum())
        label[check], upper[check] = best_label, best
    return c, assign(bank, c, "l2"), n


# ---------------------------------------------------------------- baselines
def same_position(windows: list[np.ndarray], positions: list[int] | None = None, encode=attention) -> list[np.ndarray]:
    """Rows of equal index read each other across windows; others pass."""
    out = [h.copy() for h in windows]
    for r in range(max(map(len, windows), default=0)):
        if positions is None or r in positions:
            own = [k for k, h in enumerate(windows) if len(h) > r]
            for k, v in zip(own, encode(np.stack([windows[k][r] for k in own])), strict=True):
                out[k][r] = v
    return out


def hash_labels(states: np.ndarray, vectors: np.ndarray, signed: bool = False) -> np.ndarray:
    return assign(states, np.concatenate([vectors, -vectors]) if signed else vectors, "dot")


def random_hash(states: np.ndarray, vectors: np.ndarray, stride: int, signed: bool = False, rounds: int = 1, encode=attention) -> np.ndarray:
    """Buckets of random directions in place of clusters; several rounds (slices of vectors) are averaged."""
    parts = np.array_split(vectors, rounds)
    return sum(cluster_attention(states, hash_labels(states, v, signed), stride, encode) for v in parts) / rounds


def recurrent(states: np.ndarray, decay: float = 0.5) -> np.ndarray:
    out = np.empty_like(states)
    h = np.zeros(states.shape[1])
    for i, s in enumerate(states):
        out[i] = h = decay * h + s
    return out


def carry_memory(windows: list[np.ndarray]) -> list[np.ndarray]:
    """Each window reads its own rows and those of the window before."""
    return [attention(h, np.concatenate([windows[k - 1], h]) if k else h) for k, h in enumerate(windows)]


def global_rows(states: np.ndarray, heads: np.ndarray, half: int, scale: float | None = None, step: int = 64) -> np.ndarray:
    """Attention of rows to those within half places and to the global rows (heads: their numbers), which read all rows;
    in blocks of step rows, never all by all."""
    out, n = np.empty_like(states, dtype=np.float64), len(states)
    for lo in range(0, n, step):
        a, z = max(0, lo - half), min(n, lo + step + half)
        rows, far = np.arange(lo, min(n, lo + step)), heads[(heads < a) | (heads >= z)]
        near = np.concatenate([(np.abs(rows[:, None] - np.arange(a, z)) <= half) | np.isin(np.arange(a, z), heads), np.ones((len(rows), len(far)), bool)], 1)
        out[rows] = attention(states[rows], np.concatenate([states[a:z], states[far]]), scale, near)
    for at in range(0, len(heads), step):
        out[heads[at : at + step]] = attention(states[heads[at : at + step]], states, scale)
    return out


def sorted_buckets(states: np.ndarray, direction: np.ndarray, stride: int) -> np.ndarray:
    order = np.argsort(states @ direction, kind="stable")
    out = np.empty_like(states)
    for i in range(0, len(order), stride):
        out[order[i : i + stride]] = attention(states[order[i : i + stride]])
    return out


def responsibilities(x: np.ndarray, weights: np.ndarray, means: np.ndarray, covs: np.ndarray) -> np.ndarray:
    """Share of each component of a mixture of normal distributions in each row; by logarithms, so none over- or underflows."""
    out = np.full((len(x), len(means)), -np.inf)
    for c in np.flatnonzero(weights > 0):
        low = np.linalg.cholesky(covs[c])
        z = np.linalg.solve(low, (x - means[c]).T)
        out[:, c] = np.log(weights[c]) - np.log(np.diag(low)).sum() - 0.5 * (z * z).sum(0)
    out = np.exp(out - out.max(1, keepdims=True, initial=-np.inf)) if len(x) else out
    return out / out.sum(1, keepdims=True)
