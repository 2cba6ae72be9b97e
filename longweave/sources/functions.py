"""The methods as SQL functions: token_state(tok), dot_to(a, b), cosine_to(a, b), cluster_of(vec, centroids), windows_of(x,
win, stride); and the tables as views."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from longweave.functions.kernels import TokenVectors, assign, window_bounds
from longweave.session import load


@pandas_udf("double")
def cosine_to(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.array(a.tolist(), dtype=float), np.array(b.tolist(), dtype=float)
    n = np.sqrt((x * x).sum(1) * (y * y).sum(1))
    return pd.Series(np.divide((x * y).sum(1), n, out=np.zeros(len(n)), where=n > 0))


@pandas_udf("double")
def dot_to(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.array(a.tolist(), dtype=float), np.array(b.tolist(), dtype=float)
    return pd.Series((x * y).sum(1))


@pandas_udf("array<double>")
def token_state(tok: pd.Series) -> pd.Series:
    known = TokenVectors()
    return pd.Series(list(known(tok.tolist())))


@pandas_udf("int")
def cluster_of(vec: pd.Series, centroids: pd.Series) -> pd.Series:
    """Number of the centroid nearest by cosine."""
    return pd.Series([int(assign(np.array([v], dtype=float), np.array(c.tolist() if hasattr(c, "tolist") else c, dtype=float))[0]) for v, c in zip(vec, centroids, strict=True)])


@udtf(returnType="win int, lo int, hi int")
class WindowsOf:
    def eval(self, x: int, win: int, stride: int):
        for k, (lo, hi) in enumerate(window_bounds(x, win, stride)):
            yield k, lo, hi


def register(spark: SparkSession) -> None:
    for f in (cosine_to, dot_to, token_state, cluster_of):
        spark.udf.register(f.__name__, f)
    spark.udtf.register("windows_of", WindowsOf)


def views(spark: SparkSession, sf_dir: str, names) -> None:
    """A view <name>_v of each of the tables."""
    for n in names:
        load(spark, sf_dir, n).createOrReplaceTempView(f"{n}_v")
