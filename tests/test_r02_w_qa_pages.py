"""Second review, F9: several questions go through the layers together, with the results of each alone."""

import numpy as np
import pytest

from longweave.functions import kernels as K
from longweave.operators import heads as H
from longweave.operators.fused import together
from longweave.plans import qa_queries as Q
from longweave.plans.stack import LayerPlan, common_depth


@pytest.mark.parametrize("causal", [False, True])
@pytest.mark.parametrize("layout", ["uniform", "masked"])
def test_questions_together_equal_each_alone(causal, layout):
    plans = [LayerPlan(4, (3,) if kind != "local" else (), kind=kind, d=8, heads=2, causal=causal, layout=layout) for kind in ("local", "same_position", "random_hash", "cluster")]
    states = lambda toks: np.array([K.token_vector(t, 8, 7) for t in toks]).reshape(-1, 8) / 4
    asked = [(["a", "b", "c"][: 2 + (n > 200)], [[f"w{i * j % 17}" for i in range(n // j)] for j in range(1, 4)]) for n in (1, 30, 62, 90, 250, 47, 400)]
    for (q, paras), got in zip(asked, H.read_several(plans, asked, states, common_depth(plans)), strict=True):
        for one, many in zip(H.read_all(plans, q, paras, states, common_depth(plans)), got, strict=True):
            np.testing.assert_allclose(one.feats, many.feats, atol=1e-9)
            np.testing.assert_allclose(one.pooled, many.pooled, atol=1e-9)
            assert one.words == many.words


def test_rows_that_fill_up_are_not_read():
    g = np.random.default_rng(0)
    block, h = K.Block.seeded(8, 2, seed=1), g.normal(size=(2, 9, 8))
    for size in (1.0, 1e3):
        got = block(size * h, held=np.array([9, 4]))
        np.testing.assert_allclose(got[1, :4], block(size * h[1:, :4])[0], atol=1e-9)
        np.testing.assert_allclose(got[0], block(size * h[:1])[0], atol=1e-9)


def test_no_row_is_lost_between_batches():
    import pyarrow as pa

    batches = [pa.RecordBatch.from_pylist([{"n": n} for n in part]) for part in ([5000, 5000, 1], [9000], [3], [4, 20000])]
    got = list(together(batches, lambda r: r["n"]))
    assert [r["n"] for part in got for r in part] == [5000, 5000, 1, 9000, 3, 4, 20000]
    assert all(len(part) == 1 or sum(r["n"] for r in part) <= 8192 for part in got)


def test_pages_are_cut_into_paragraphs_once(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(Q, "_compare", lambda spark, sf, paras: seen.append(paras))
    Q.w_qa_pages(spark, sf)
    assert "regexp" not in seen[0]._jdf.queryExecution().toString().lower()
