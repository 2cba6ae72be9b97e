"""Second review, F5: several segments go through the layers together; vectors of new words are made together."""

import hashlib

import numpy as np

from longweave.functions import kernels as K
from longweave.operators import lm as L
from longweave.plans.stack import LayerPlan, common_depth


def test_segments_together_equal_each_alone():
    plans = [LayerPlan(4, (3,) if kind != "local" else (), kind=kind, win=32, stride=16, d=8, heads=2, causal=True) for kind in ("local", "same_position", "random_hash", "cluster")]
    g = np.random.default_rng(0)
    xs, nxts = [g.integers(-8, 9, (n, 8)) / 8.0 for n in (1, 40, 150, 33, 7)], [g.integers(0, 9, n) for n in (1, 40, 150, 33, 7)]
    for x, nxt, each in zip(xs, nxts, L.copy_scores_several(plans, xs, nxts, common_depth(plans)), strict=True):
        for plan, got in zip(plans, each, strict=True):
            np.testing.assert_allclose(got, L.copy_scores(plan, x, nxt), atol=1e-12)
            at = L.looks(plan)
            states = plan.encode(x, below=at)[0]
            h, out, n = plan.blocks()[0].norm(states), np.zeros(len(x)), np.zeros(len(x))
            for rows in L.attended(plan, states, at) if plan.cal else [np.arange(*w) for w in K.window_bounds(len(x), 32, 16)]:
                for i in rows:
                    past = rows[rows < i]
                    if len(past):
                        e = np.exp(2.0 / 8**0.5 * h[past] @ h[i])
                        out[i] += e[nxt[past] == nxt[i]].sum() / e.sum()
                        n[i] += 1
            np.testing.assert_allclose(got[1], out / np.maximum(n, 1), atol=1e-9)


def test_vectors_of_words_made_together():
    want = lambda t: [int(hashlib.md5(f"{t}:{j}:7".encode()).hexdigest()[:8], 16) % 17 - 8 for j in range(5)]
    known, calls = K.TokenVectors(5, 7), (["a", "é", "a", ""], [], ["b", "a", "b", "c"], [f"w{i}" for i in range(50)])
    for toks in calls:
        np.testing.assert_array_equal(known(toks), np.array([want(t) for t in toks]).reshape(-1, 5))
    known.most = 10
    np.testing.assert_array_equal(known(["z", "a"]), [want("z"), want("a")])
