"""Second review, F12: layers that methods share run once for all of them, and texts of questions nobody looks at stay where they are."""

import numpy as np
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.operators import heads as H
from longweave.plans import qa_queries as Q
from longweave.plans.stack import LayerPlan, common_depth


def test_layers_shared_by_methods_run_once(monkeypatch):
    plans = [LayerPlan(4, (3,) if kind != "local" else (), kind=kind, d=8, heads=2) for kind in ("local", "same_position", "cluster")]
    states = lambda toks: np.array([K.token_vector(t, 8, 7) for t in toks]).reshape(-1, 8)
    q, paras = ["a", "b"], [[f"w{i * j % 17}" for i in range(90)] for j in range(1, 4)]
    alone = [H.read(p, q, paras, states) for p in plans]
    calls, plain = [], K.encode_merged
    monkeypatch.setattr(K, "encode_merged", lambda *a, **k: (calls.append(1), plain(*a, **k))[1])
    assert common_depth(plans) == 3 and common_depth([plans[0], LayerPlan(4, (3,), d=8, heads=4)]) == 1
    for one, got in zip(alone, H.read_all(plans, q, paras, states, 3), strict=True):
        np.testing.assert_array_equal(one.feats, got.feats)
        assert one.words == got.words
    assert len(calls) == 2 + 2 + 1 + 1  # layers 1 and 2 once, 3 and 4 of the first, 4 of the others


def test_attention_equals_its_definition():
    g = np.random.default_rng(0)
    q, k, v = g.normal(size=(3, 2, 3, 50, 4))
    for size in (1.0, 1e3):  # the second overflows without a shift
        for mask in (None, np.tril(np.ones((50, 50), bool)), (g.random((2, 50, 50)) < 0.3) | np.eye(50, dtype=bool)):
            s = size * q @ k.swapaxes(-1, -2)
            if mask is not None:
                s = np.where(mask if mask.ndim == 2 else mask[:, None], s, -np.inf)
            s = np.exp(s - s.max(-1, keepdims=True))
            np.testing.assert_allclose(K.soft_read(size * q, k, v, mask), s / s.sum(-1, keepdims=True) @ v, atol=1e-9)


def test_only_questions_somebody_looks_at(spark, sf, monkeypatch):
    monkeypatch.setattr(Q, "FIT_ROWS", 7)
    paras = Q.line_paras(spark, sf)
    every = {r["seq_id"]: r for r in Q.questions(paras).withColumn("h", F.xxhash64("seq_id")).collect()}
    first = sorted((r["h"], k) for k, r in every.items() if r["fold"] != "test")[:7]
    got = Q.questions(paras, Q.asked(paras).filter("fit or fold = 'test'")).collect()
    assert {r["seq_id"] for r in got} == {k for _, k in first} | {k for k, r in every.items() if r["fold"] == "test"}
    assert all(r[c] == every[r["seq_id"]][c] for r in got for c in r.asDict())
