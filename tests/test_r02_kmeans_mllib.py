"""Second review, F14: a mixture with near-singular components."""

import numpy as np

from longweave.plans import registry

registry.everything()


def test_mixture_of_near_singular_components(spark):
    """The library's mixture failed on the table of sf0.01 (its covariance became NaN)."""
    rows = {r["way"]: r for r in registry.QUERIES["kmeans_mllib"](spark, "/root/testdata/sf0.01").collect()}
    assert set(rows) == {"kmeans", "bisecting", "mixture"}
    assert 0 < rows["mixture"]["mean_square"] < 1.5 and rows["mixture"]["clusters"] <= 10


def test_mixture_finds_two_clouds_and_bears_copies(spark):
    from longweave.operators import clusters as C

    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(size=(200, 2)) * [1, 0.1], rng.normal(size=(100, 2)) * [0.1, 1] + 5, np.full((50, 2), 9.0)])
    df = spark.createDataFrame([(v.tolist(),) for v in x], "vec array<double>")
    w, m, cov = C.mixture(df, np.array([[0.5, 0.5], [4.5, 4.5], [9.0, 9.0]]), 10)
    assert np.allclose(w, [200 / 350, 100 / 350, 50 / 350], atol=0.02) and np.allclose(m, [[0, 0], [5, 5], [9, 9]], atol=0.3)
    assert np.isfinite(cov).all()
