"""Third review, F2, F3, F4: dense attention takes one exponential for two rows, groups of one size go together, and few
partners of a row are looked at in double precision; results are those of the definitions."""

import time

import numpy as np
import pytest

from longweave.functions import kernels as K
from longweave.plans import workload_queries as W


@pytest.mark.parametrize("n", [2, 3, 300, 1500])
@pytest.mark.parametrize("size", [1.0, 30.0])  # the second overflows without a shift
def test_attention_among_all_rows_takes_half_the_exponentials(n, size, monkeypatch):
    x = size * np.random.default_rng(n).normal(size=(n, 8))
    want, taken, real = K.attention(x, x.copy(), W.SCALE), [], np.exp
    monkeypatch.setattr(np, "exp", lambda s, *a, **k: (taken.append(s.size), real(s, *a, **k))[1])
    np.testing.assert_allclose(K.attention(x, x, W.SCALE), want, rtol=1e-9, atol=1e-9)
    assert n < 1000 or size > 1 or sum(taken) < 0.6 * n * n


def test_one_state_many_times():
    x = np.concatenate([np.tile(np.arange(8.0), (400, 1)), np.random.default_rng(0).normal(size=(300, 8)), np.zeros((20, 8))])
    s = np.round(x @ x.T, 6)
    np.fill_diagonal(s, -np.inf)
    np.testing.assert_array_equal(W.strongest(x, 8), np.argsort(-s, 1, kind="stable")[:, :8])
    far = np.random.default_rng(1).normal(size=(260, 8)) * 1e5
    s = far @ far.T
    np.fill_diagonal(s, -np.inf)
    np.testing.assert_array_equal(W.strongest(far, 8), np.argsort(-s, 1, kind="stable")[:, :8])


def test_groups_that_overlap_or_do_not():
    x = np.random.default_rng(2).normal(size=(333, 8))
    for kind in ("local", "same_position", "random_hash", "cluster"):
        groups = W.swap_groups(kind, x, x[:64], x[:64])
        out, count, of = np.zeros_like(x), np.zeros(len(x)), [[] for _ in x]
        for k, rows in enumerate(groups):
            out[rows] += K.attention(x[rows], scale=W.SCALE)
            count[rows] += 1
            for r in rows.tolist():
                of[r].append(k)
        got, ids = W.within_groups(x, groups)
        np.testing.assert_allclose(got, out / count[:, None], rtol=1e-12, atol=1e-12)
        assert [[k for k in line if k >= 0] for line in ids.tolist()] == of


def test_calls_do_not_grow_with_groups(monkeypatch):
    x = np.random.default_rng(3).normal(size=(4800, 8))
    groups, took = W.swap_groups("cluster", x, x[:64]), []
    monkeypatch.setattr(K, "attention", None)  # before: a call for each group
    began = time.perf_counter()
    W.within_groups(x, groups)
    took.append(time.perf_counter() - began)
    assert took[0] < 5


def test_numbers_of_centroids_share_a_bank(spark, sf, monkeypatch):
    from longweave.operators import refresh as R
    from longweave.plans import method_queries as M

    how = R.Refresh(cap=500, iterations=2, every=1, steps=2)
    want = [M.text_snapshots(spark, sf, p, how) for p in (4, 8)]
    monkeypatch.setattr(M, "_fitted", {})
    pushed, real = [], R.MemoryBank.push
    monkeypatch.setattr(R.MemoryBank, "push", lambda *a: pushed.append(1) or real(*a))
    got = M.several_snapshots(spark, sf, (4, 8), how)
    assert len(pushed) == 2  # one for each iteration, in place of one for each iteration and number
    for a, b in zip(got, want, strict=True):
        np.testing.assert_array_equal(a[-1].ordered, b[-1].ordered)
    assert M.text_snapshots(spark, sf, 8, how) is got[1] and len(pushed) == 2


def test_a_sweep_makes_one_bank(spark, sf, monkeypatch):
    from longweave.plans import method_queries as M

    passes, real = [], M.refresh_loops
    small = M.Refresh(cap=300, iterations=1, every=1, steps=1)
    monkeypatch.setattr(M, "_fitted", {})
    monkeypatch.setattr(M, "refresh_loops", lambda packed, encode, inits, how: passes.append([len(x) for x in inits]) or real(packed, encode, inits, small))
    assert list(W.sweep_kinds(spark, sf)) == [16, 64, 256, 512] and passes == [[16, 64, 256, 512]]
