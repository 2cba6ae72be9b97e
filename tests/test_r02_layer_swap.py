"""Second review, F6, F7, F11: the dense side of a document is made once, whatever is held against it."""

import numpy as np

from longweave.plans import registry
from longweave.plans import workload_queries as Q

registry.everything()


def test_strongest_partners_with_ties():
    x = np.random.default_rng(0).integers(-2, 3, (70, 3)).astype(float)
    s = np.round(x @ x.T, 6)
    np.fill_diagonal(s, -np.inf)
    for top in (1, 8, 200):
        np.testing.assert_array_equal(Q.strongest(x, top), np.argsort(-s, 1, kind="stable")[:, : min(top, 69)])


def test_dense_attention_runs_once_for_all_ways(monkeypatch):
    x = np.random.default_rng(1).normal(size=(150, 4))
    ways = [Q.swap_groups("local", x), Q.swap_groups("same_position", x), Q.swap_groups("cluster", x, x[:5])]
    alone = [Q.against_dense(x, [w])[0] for w in ways]
    calls, plain = [], Q.K.attention
    monkeypatch.setattr(Q.K, "attention", lambda *a, **k: (calls.append(len(a)), plain(*a, **k))[1])
    together = Q.against_dense(x, ways)
    assert calls.count(3) == 1  # against all rows
    np.testing.assert_allclose(together, alone)
