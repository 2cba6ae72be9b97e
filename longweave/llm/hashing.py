"""Vectorised word hashing: every word of a block of texts gets a 64-bit hash without a Python loop over words."""

from __future__ import annotations

import numpy as np

U = np.uint64
_rng = np.random.Generator(np.random.PCG64(20240229))
#: A random odd number for each byte value; white space counts nothing.
BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
BYTE[SPACE] = 0
BASE = U(0x9E3779B97F4A7C15)
_power = np.cumprod(np.concatenate(([U(1)], np.full(1 << 12, BASE, dtype=np.uint64))), dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits with full avalanche."""
    x = np.asarray(x, dtype=np.uint64)
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def powers(n: int) -> np.ndarray:
    global _power
    if n > len(_power):
        _power = np.cumprod(np.concatenate(([U(1)], np.full(2 * n, BASE, dtype=np.uint64))), dtype=np.uint64)
    return _power[:n]


def words_of(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(start byte, hash) of each maximal run of non-white-space bytes in raw."""
    b = np.frombuffer(raw, dtype=np.uint8)
    if not len(b):
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    space = SPACE[b]
    word = ~space
    first = word.copy()
    first[1:] &= space[:-1]
    start = np.flatnonzero(first)
    if not len(start):
        return start, np.empty(0, np.uint64)
    at = np.arange(len(b)) - np.repeat(start, np.diff(np.append(start, len(b)))) if start[0] == 0 else None
    if at is None:
        at = np.zeros(len(b), dtype=np.int64)
        at[start[0] :] = np.arange(start[0], len(b)) - np.repeat(start, np.diff(np.append(start, len(b))))
    h = np.add.reduceat(BYTE[b] * powers(int(at.max()) + 1)[at], start)
    return start, mix(h)


def blocks(texts: list[str | None], most: int = 1 << 20):
    """Consecutive runs of texts of about `most` characters: (first index, texts)."""
    at, size = 0, 0
    for i, x in enumerate(texts):
        size += len(x or "")
        if size >= most:
            yield at, texts[at : i + 1]
            at, size = i + 1, 0
    if at < len(texts):
        yield at, texts[at:]


def hashed(texts: list[str | None], lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts in order, and the bounds (len(texts) + 1) of each text's words.

    lower: only A-Z are lowered.  Words are separated by space, tab, line feed, vertical tab, form feed, carriage return.
    """
    raw = [(x or "").encode("utf-8", "surrogatepass") for x in texts]
    whole = b"\n".join(raw)
    if lower:
        whole = whole.lower()
    start, h = words_of(whole)
    ends = np.cumsum([len(x) + 1 for x in raw])
    return h, np.concatenate(([0], np.searchsorted(start, ends)))


def ngrams(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each window of n consecutive words (over text bounds too; callers drop those)."""
    if len(h) < n:
        return np.empty(0, np.uint64)
    out = np.zeros(len(h) - n + 1, dtype=np.uint64)
    for j in range(n):
        out = (out + h[j : len(h) - n + 1 + j]) * U(0xD6E8FEB86659FD93)
    return mix(out)
