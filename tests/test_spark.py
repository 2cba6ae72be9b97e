"""Long form against kernels, plans, and queries against DuckDB on the smallest tables."""

import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.operators import clusters as C
from longweave.operators import windows as W
from longweave.operators.bank import MemoryBank
from longweave.operators.measures import answer_prf, token_f1
from longweave.plans import registry

registry.everything()


def vectors(spark, n=60, d=4):
    v = np.random.default_rng(0).normal(size=(n, d))
    return v, spark.createDataFrame([(0, i, x.tolist()) for i, x in enumerate(v)], "seq_id long, pos int, vec array<double>")


def test_long_windows_equal_kernels(spark):
    v, df = vectors(spark)
    spec = W.WindowSpec(16, 12)
    w = W.slice_windows(df, spec)
    merged = W.merge_overlaps(w.withColumn("vec", F.transform("vec", lambda x: x * (F.col("win") + 1))), spec)
    got = {(r["win"], r["row"]): r["vec"] for r in merged.collect()}
    want = K.merge_overlaps([h * (k + 1) for k, h in enumerate(K.slice_windows(v, np.empty((0, 4)), 16, 12))], 0, 60, 16, 12)
    for k, h in enumerate(want):
        for r, x in enumerate(h):
            np.testing.assert_allclose(got[k, r], x)
    assert W.dedup_concat(w, spec).count() == 60
    back = W.unpack(W.pack(w), 4)
    assert back.join(w, ["seq_id", "win", "row", "vec"], "left_semi").count() == w.count()
    with pytest.raises(ValueError):
        W.merge_overlaps(w, W.WindowSpec(30, 12), "pair_mean")


def test_ranks_agree_and_fast_labels_agree(spark):
    v, df = vectors(spark)
    chained = C.chain(spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v[:5])], "cid int, vec array<double>"))
    s = C.nearest(df.withColumn("hpos", F.col("pos")), chained)
    cent = np.array([r["vec"] for r in chained.orderBy("ord").collect()])
    fast = {r["pos"]: r["cluster"] for r in C.nearest_fast(df, cent).collect()}
    assert {r["pos"]: r["cluster"] for r in s.collect()} == fast
    one = {r["pos"]: r["srank"] for r in C.cluster_rank(s).collect()}
    assert one == {r["pos"]: r["srank"] for r in C.cluster_rank_counting(s, 7).collect()}


def test_kmeans_distributed_equals_kernel(spark):
    v, df = vectors(spark, 200)
    np.testing.assert_allclose(C.kmeans(df, v[:6], 5), K.kmeans(v, v[:6], 5)[0])


def test_bank_keeps_the_newest(spark, tmp_path):
    bank = MemoryBank(spark, f"file://{tmp_path}/bank", cap=3)
    for k, rows in enumerate([[(1,), (2,)], [(3,), (4,)]]):
        bank.push(spark.createDataFrame(rows, "arrival long"), k)
        bank.push(spark.createDataFrame(rows, "arrival long"), k)  # again: no change
    assert sorted(r["arrival"] for r in bank.read().collect()) == [2, 3, 4]


def test_answer_measures(spark):
    df = spark.createDataFrame([("red big house", "red house"), (None, None), ("x", None), (None, "y")], "pred string, gold string")
    assert [round(r["f"], 3) for r in df.select(token_f1("pred", "gold").alias("f")).collect()] == [0.8, 1.0, 0.0, 0.0]
    r = answer_prf(df).first()
    assert (r["tp"], r["fp"], r["fn"]) == (0, 2, 1)
    assert answer_prf(df, wrong_counts_as_fn=True).first()["fn"] == 2
    for p, q, f in ((78.5, 77.5, 78.0), (62.1, 59.8, 60.9)):
        assert round(2 * p * q / (p + q), 1) == f


def test_cluster_attention_needs_no_shuffle(spark, sf):
    plan = registry.QUERIES["cal_text_states"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan
    labels = registry.QUERIES["assign_cosine"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in labels


SOME = ["refresh_snapshots", "cal_masked", "cal_padded", "cal_unordered", "centroid_select_best", "bank_after_batches", "win_encode_padded", "win_position_codes", "base_select_concat", "base_global_tokens", "m_token_f1", "m_sentinel_colocation", "w_cluster_report", "w_dataset_stats", "stream_state_totals", "join_semi_gold", "cal_attn_vectors", "centroid_chain", "win_membership", "win_encode_attn", "cal_text_states", "base_random_hash", "qa_best_span", "m_answer_prf", "m_attention_recall", "w_dialog_qa", "join_asof_signup", "join_interval_click", "agg_rollup_lang_source", "win_islands", "stream_session", "udtf_windows"]


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, sf, name):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    want = c.sql(registry.ORACLES[name])
    cols = sorted(want.columns)
    clean = lambda r: tuple("" if x is None else f"{x:.5f}" if isinstance(x, float) else str(x) for x in r)
    rows = sorted(clean(r) for r in want.select(*(f'"{k}"' for k in cols)).fetchall())
    assert rows == sorted(clean(r) for r in registry.QUERIES[name](spark, sf).select(*cols).collect())


def test_every_oracle_has_its_query():
    assert set(registry.ORACLES) <= set(registry.QUERIES)


def test_kmeans_ways_share_the_whole_bank(spark, sf):
    from longweave.plans import workload_queries as Q

    from longweave.plans.method_queries import doc_tokens

    total = doc_tokens(spark, sf).count()
    assert Q.kmeans_bounded(spark, sf).first()["n"] == min(100_000, total)
    assert Q.state_bank(spark, sf, cap=30).count() == 30


def test_refresh_pushes_evicts_fits_then_labels(spark):
    """A stream made by hand: the order of the steps, the cap, and what the next labels see."""
    from longweave.operators.refresh import Refresh, refresh_loop

    seen = {0: [[0.0, 1.0]] * 3, 1: [[1.0, 0.0]] * 2, 2: [[4.0, 0.0], [0.0, 4.0]], 3: [[6.0, 0.0], [0.0, 8.0]]}
    packed = spark.createDataFrame([(k, [str(k)]) for k in seen], "seq_id long, toks array<string>")
    init = np.array([[1.0, 0.1], [0.1, 1.0]])
    got = refresh_loop(packed, lambda toks: np.array(seen[int(toks[0])]), init, Refresh(cap=4, iterations=4, every=2, steps=1))
    assert [s.epoch for s in got] == [1, 2]
    # after two iterations five states came, the newest four are held: [0,1] twice, [1,0] twice
    np.testing.assert_allclose(got[0].centroids, [[1.0, 0.0], [0.0, 1.0]])
    # after four, only those of the last two iterations
    np.testing.assert_allclose(got[1].centroids, [[5.0, 0.0], [0.0, 6.0]])
    bank, c = np.empty((0, 2)), init
    for i, states in enumerate(seen.values(), 1):
        bank = np.concatenate([bank, states])[-4:]
        c = K.kmeans(bank, c, 1)[0] if i % 2 == 0 else c
    np.testing.assert_allclose(got[-1].centroids, c)
    assert K.assign(np.array([[3.0, 0.1]]), got[-1].ordered).tolist() == [0]


def test_newest_sequences_and_eviction(spark, tmp_path):
    from longweave.operators.refresh import newest_sequences

    rng = np.random.default_rng(0)
    n = rng.integers(1, 9, 5000)
    lengths = spark.createDataFrame([(i * 7, int(x)) for i, x in enumerate(n)], "seq_id long, n long")
    for cap in (1, 100, 7000, 10**9):
        since, total = 0, 0
        for i in range(4999, -1, -1):
            total += n[i]
            if total >= cap:
                since = i * 7
                break
        assert newest_sequences(lengths, cap, 0, 4999 * 7) == since
    bank = MemoryBank(spark, f"file://{tmp_path}/b", cap=3)
    for k in range(3):
        bank.push(spark.createDataFrame([(2 * k,), (2 * k + 1,)], "arrival long"), k)
        bank.evict()
    assert sorted(os.listdir(tmp_path / "b")) == ["iter=1", "iter=2"]
    assert sorted(r["arrival"] for r in bank.read().collect()) == [3, 4, 5]


def test_stack_centroids_are_fitted_below_their_depth(spark, sf):
    from longweave.operators.fused import states_of
    from longweave.operators.refresh import Refresh, fit_stack
    from longweave.plans.method_queries import docs_packed
    from longweave.plans.stack import LayerPlan

    plan = LayerPlan.explicit([2, 4], n_layers=4, p=8)
    packed = docs_packed(spark, sf)
    fitted = fit_stack(packed, plan, lambda toks: states_of(toks, 8, 7), Refresh(cap=2000, iterations=1, every=1, steps=3))
    assert sorted(fitted.fitted) == [2, 4]
    for depth in (2, 4):
        states, held = [], 0
        for r in packed.orderBy(F.desc("seq_id")).limit(400).collect():
            if r["toks"] and held < 2000:
                states.append(fitted.run(states_of(r["toks"], 8, 7), below=depth))
                held += len(states[-1])
        x = np.concatenate(states[::-1])[-2000:]
        want = K.kmeans(x, plan.directions(depth), 3)[0]
        np.testing.assert_allclose(fitted.fitted[depth], want[K.chain_order(want)], atol=1e-9)


def test_no_pairs_of_documents_and_passages(spark, sf):
    for name in ("base_select_then_read", "win_question_prefix", "join_semi_gold", "w_phrase_qa"):
        plan = registry.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan, name


def test_mixture_weights_rise_the_likelihood(spark):
    from longweave.operators.lm import mixture_weights

    rows = [("m", 0.9, 0.1), ("m", 0.8, 0.1), ("m", 0.1, 0.7), ("k", 0.2, 0.6)]
    w = mixture_weights(spark.createDataFrame(rows, "method string, a double, b double"), ["a", "b"], "method", 20)
    grid = np.linspace(0, 1, 1001)
    best = grid[np.argmax([sum(np.log(g * a + (1 - g) * b) for m, a, b in rows if m == "m") for g in grid])]
    assert abs(w["m"][0] - best) < 0.02 and w["k"][1] > 0.99
