"""Second review, F8: what w_ensemble did over and over or on rows that nothing needs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.operators import refresh as R
from longweave.plans import qa_queries as Q
from longweave.plans.stack import LayerPlan


def test_only_documents_that_heads_are_fitted_on_are_cut_into_lines(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(Q, "plans_for", lambda *a: [])
    monkeypatch.setattr(Q, "readings", lambda spark, qs, plans: seen.append(qs))
    Q.two_phase(spark, sf, (), (0,))
    plan = seen[0]._jdf.queryExecution().optimizedPlan().toString()
    for part in plan.split("Generate")[1:]:  # what stands below each
        assert "LeftSemi" in part.split("Generate")[0]
    paras = Q.line_paras(spark, sf)
    want = Q.questions(paras, Q.asked(paras).filter("fit"))
    rows = lambda df: sorted(map(repr, df.collect()))
    assert rows(seen[0]) == rows(want)


def test_stacks_over_other_layers_share_what_their_banks_are_made_of(spark, monkeypatch):
    toks = spark.range(40).select(F.col("id").alias("seq_id"), F.transform(F.sequence(F.lit(0), F.col("id") % 7 + 20), lambda i: F.concat(F.lit("w"), F.col("id") * i % 31)).alias("toks"))
    plans = [LayerPlan(4, (3,), d=8, p=4, win=16, stride=8) for _ in range(3)]
    for k, plan in enumerate(plans):
        plan._made["b"] = [K.Block.seeded(8, 2, seed=10 * k + i) for i in range(4)]
    vectors, how = (lambda t: K.token_vectors(t, 8, 7) / 6), R.Refresh(cap=300, iterations=2, every=1, steps=2)
    want = [R.fit_stack(toks, plan, vectors, how) for plan in plans]
    passes, real = [], R.persist_cut
    monkeypatch.setattr(R, "persist_cut", lambda df: passes.append(df.columns) or real(df))
    got = R.fit_stacks(toks, plans, vectors, how)
    assert passes.count(["seq_id", "n"]) == 1
    for a, b in zip(got, want, strict=True):
        np.testing.assert_array_equal(a.centroids(3), b.centroids(3))


def test_nearest_centroids_need_few_products_in_double_precision(monkeypatch):
    g = np.random.default_rng(1)
    c = g.normal(size=(512, 16))
    c[400], c[200], c[300] = c[7], 3 * c[9], 0
    x = np.concatenate([g.normal(size=(2000, 16)), c[:20] * 5, np.zeros((2, 16)), g.normal(size=(5, 16)) * 1e120, g.normal(size=(5, 16)) * 1e-120])
    want, rows, real = K.similarity(x, c).argmax(1), [], K.similarity
    monkeypatch.setattr(K, "similarity", lambda s, *a: rows.append(len(s)) or real(s, *a))
    np.testing.assert_array_equal(K.assign(x, c), want)
    assert sum(rows) < 200


@pytest.mark.parametrize("n", [1, 5, 72, 700])
@pytest.mark.parametrize("large", [1.0, 40.0])
def test_a_block_reads_along_long_axes(n, large, monkeypatch):
    g = np.random.default_rng(2)
    b, h = K.Block.seeded(16, 4, seed=3), g.normal(size=(3, n, 16))
    b.wq, b.wk = b.wq * large, b.wk * large
    b.gain, b.shift = g.normal(size=16), g.normal(size=16)
    held = np.array([n, max(1, n // 2), 1])
    every = np.ones((n, n), bool)
    want, some = b(h, every), b(h, every, held=held)
    monkeypatch.setattr(K, "soft_read", None)  # rows by coordinates; a block without a mask needs it no more
    np.testing.assert_allclose(b(h), want, rtol=1e-9, atol=1e-9)
    own = np.arange(n) < held[:, None]
    assert np.isfinite(some[own]).all()
    np.testing.assert_allclose(b(h, held=held)[own], some[own], rtol=1e-9, atol=1e-9)
