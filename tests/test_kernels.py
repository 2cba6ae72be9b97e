"""Worked cases and invariants of the dense kernels."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from longweave.functions import kernels as K
from longweave.plans.stack import LayerPlan

CENT = np.array([[1, 0], [0, 1], [3, 1], [-1, 0.2]])
STATES = np.array([[2, 0], [0, 3], [1, 1], [-2, 0], [3, 1], [0, -1.0]])


def test_windows_are_ragged_and_checked():
    assert K.window_bounds(5, 3, 2) == [(0, 3), (2, 5), (4, 5)]
    assert K.window_bounds(0, 3, 2) == []
    with pytest.raises(ValueError):
        K.window_bounds(5, 2, 2)


def test_merge_reads_values_from_before():
    enc = [np.array([[100], [10], [11], [12.0]]), np.array([[200], [22], [23], [24.0]]), np.array([[300], [34.0]])]
    got = K.merge_overlaps(enc, 1, 5, 3, 2)
    assert [x.ravel().tolist() for x in got] == [[100, 10, 11, 17], [200, 17, 23, 29], [300, 29]]
    flat = K.dedup_concat(got, 1, 2)
    assert flat.ravel().tolist() == [100, 10, 11, 200, 17, 23, 300, 29]
    assert all(np.array_equal(a, b) for a, b in zip(K.rewindow(flat, 1, 5, 3, 2), got, strict=True))


def test_chain_labels_blocks_and_attention():
    order = K.chain_order(CENT)
    assert order == [0, 2, 1, 3]
    lab = K.assign(STATES, CENT[order])
    assert lab.tolist() == [0, 2, 1, 3, 1, 0]
    assert [b.tolist() for b in K.blocks_of(lab, 3)] == [[0, 5, 2], [4, 1, 3]]
    out, full = K.cluster_attention(STATES, lab, 3), K.attention(STATES)
    np.testing.assert_allclose(out[0], [1.722530, 0.141305], atol=1e-6)
    np.testing.assert_allclose(full[3], [-1.738107, 0.117361], atol=1e-6)
    assert abs(np.linalg.norm(out - full) / np.linalg.norm(full) - 0.275484) < 1e-6


def test_degenerate_cases_meet():
    x = np.random.default_rng(0).normal(size=(37, 8))
    lab = K.assign(x, x[:5])
    np.testing.assert_allclose(K.cluster_attention(x, lab, 64), K.attention(x))  # one block is dense attention
    same = lambda h: h
    assert np.array_equal(K.cluster_attention(x, lab, 7, same), x)  # order comes back
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert np.array_equal(K.hash_labels(x, unit[:5]), K.assign(x, unit[:5]))
    assert K.assign(np.zeros((1, 8)), x[:5]).tolist() == [0]
    strict = K.blocks_of(lab, 7, "strict")
    assert all(len(set(lab[b])) == 1 for b in strict) and sorted(np.concatenate(strict)) == list(range(37))


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 60), st.integers(2, 9), st.integers(1, 8), st.integers(0, 3))
def test_dedup_has_each_context_row_once(x, win, stride, q):
    if stride >= win:
        return
    h = np.arange(x, dtype=float)[:, None]
    wins = K.slice_windows(h, -np.ones((q, 1)), win, stride)
    flat = K.dedup_concat(wins, q, stride)
    assert len(flat) == q * -(-x // stride) + x
    assert flat[flat >= 0].tolist() == list(range(x))


def test_bounded_kmeans_equals_lloyd_with_fewer_distances():
    g = np.random.default_rng(3)
    x = g.normal(size=(1500, 6))
    a, b = K.kmeans(x, x[:40], 12), K.kmeans_bounded(x, x[:40], 12)
    assert np.array_equal(a[1], b[1]) and np.allclose(a[0], b[0]) and b[2] < a[2]


def test_layer_plans():
    assert LayerPlan.modulo(5, 12).cal == (15, 20) and LayerPlan.explicit([20, 15]).cal == (15, 20)
    assert LayerPlan.modulo(6, 20, base=1).cal == (24,) and LayerPlan.lm().cal == (11, 15)
    with pytest.raises(ValueError):
        LayerPlan.explicit([1])
    x = np.random.default_rng(1).normal(size=(200, 8))
    assert LayerPlan.explicit([2, 4], n_layers=4).run(x).shape == (200, 8)


def test_causal_stack_reads_no_later_state():
    x = np.random.default_rng(1).normal(size=(90, 16))
    plan = LayerPlan.explicit([2], n_layers=2, causal=True, win=200, stride=150, d=16)
    y = x.copy()
    y[60:] += 1
    np.testing.assert_allclose(plan.run(x)[:60], plan.run(y)[:60])


def test_batches_equal_one_by_one():
    g = np.random.default_rng(2)
    x, q = g.normal(size=(150, 8)), g.normal(size=(3, 8))
    block = K.Block.seeded(8, 2)
    ctx, qs = K.encode_merged(x, np.repeat(q[None], -(-150 // 20), 0), 32, 20, block)
    want = K.merge_overlaps([block(h) for h in K.slice_windows(x, q, 32, 20)], 3, 150, 32, 20)
    flat = K.dedup_concat(want, 3, 20)
    np.testing.assert_allclose(LayerPlan(1, win=32, stride=20).flat(ctx, qs), flat)
    lab = K.assign(x, x[:6])
    for layout in ("uniform", "strict", "padded", "masked"):
        one = np.empty_like(x)
        for rows in K.blocks_of(lab, 16, layout):
            one[rows] = K.attention(x[rows], mask=lab[rows][:, None] == lab[rows] if layout == "masked" else None)
        np.testing.assert_allclose(K.cluster_attention(x, lab, 16, layout=layout), one)


def test_same_position_layer_equals_kernel():
    x = np.random.default_rng(3).normal(size=(130, 8))
    plan = LayerPlan.explicit([2], n_layers=2, kind="same_position", win=32, stride=20)
    none = np.empty((0, 8))
    wins = K.merge_overlaps([plan.blocks()[0](h + K.position_codes(32, 8)[: len(h)]) for h in K.slice_windows(x, none, 32, 20)], 0, 130, 32, 20)
    wins = K.merge_overlaps(K.same_position(wins, None, plan.blocks()[1]), 0, 130, 32, 20)
    np.testing.assert_allclose(plan.run(x), K.dedup_concat(wins, 0, 20))


def test_global_rows_equal_the_dense_mask():
    x = np.random.default_rng(4).normal(size=(200, 6))
    heads = np.arange(0, 200, 50)
    at, known = np.arange(200), np.isin(np.arange(200), heads)
    want = K.attention(x, mask=(np.abs(at[:, None] - at) <= 7) | known[None] | known[:, None])
    np.testing.assert_allclose(K.global_rows(x, heads, 7, step=16), want)


def test_dropout_only_in_training():
    block = K.Block.seeded(8, 2)
    block.drop = 0.5
    x = np.random.default_rng(5).normal(size=(10, 8))
    assert np.array_equal(block(x), block(x)) and not np.allclose(block(x), block(x, rng=np.random.default_rng(0)))


def test_copying_reads_the_past_only():
    from longweave.operators.lm import copy_mass

    h = np.eye(4)[[0, 1, 0, 1, 0]]
    nxt = np.array([1, 0, 1, 0, 2])
    got = copy_mass(h, nxt, [np.arange(5)], 50.0)
    np.testing.assert_allclose(got, [0, 0, 1, 1, 0], atol=1e-9)
    assert copy_mass(h, nxt, [np.array([r]) for r in range(5)], 50.0).sum() == 0


def test_heads_learn_and_abstain():
    from longweave.operators import heads as H

    g, rows = np.random.default_rng(6), []
    for i in range(300):
        f = np.concatenate([np.ones((5, 1)), g.normal(size=(5, 4))], 1)
        gold = int(g.integers(0, 5)) if i % 2 else None
        if gold is not None:
            f[gold, 1] += 6
        rows.append({"feats": f, "pooled": g.normal(size=3), "gold": gold, "dev": i % 5 == 0})
    fitted = H.fit_heads(rows, H.Knobs(updates=400))
    right = np.mean([H.answered(fitted, r["feats"], r["pooled"]) == r["gold"] for r in rows])
    assert right > 0.9 and set(fitted.dev) == set(H.DROPOUTS)
    k = H.Knobs(updates=100, warm_up=10)
    assert k.rate_at(9) == k.rate and k.rate_at(0) == k.rate / 10 and k.rate_at(100) == 0
    again = H.fit_heads(rows, H.Knobs(updates=0), init=fitted, dropouts=(0.1,))
    assert np.array_equal(again.para, fitted.para)  # a second phase starts from the first
    assert H.f1([(1, 1), (None, None), (2, 3), (None, 4)]) == 2 / 4
