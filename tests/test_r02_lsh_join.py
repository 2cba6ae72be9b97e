"""Second review, F2: pairs that share a bucket, by products of blocks, equal the model's own join."""

import numpy as np
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector
from pyspark.sql import functions as F

from longweave.plans.operator_queries import bucket_pairs


def test_pairs_equal_the_models_join(spark):
    g = np.random.default_rng(0)
    x = np.concatenate([g.normal(size=(150, 6)) * 0.4, np.zeros((3, 6))])
    v = spark.createDataFrame([(k, r.tolist()) for k, r in enumerate(x)], "vec_id long, e array<double>").select("vec_id", array_to_vector("e").alias("f"))
    m = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=0.5, numHashTables=3, seed=1).fit(v)
    j = m.approxSimilarityJoin(v, v, 0.7, "dist").filter("datasetA.vec_id < datasetB.vec_id")
    want = {(r["a"], r["b"], r["d"]) for r in j.select(F.col("datasetA.vec_id").alias("a"), F.col("datasetB.vec_id").alias("b"), F.round("dist", 6).alias("d")).collect()}
    for block in (8192, 40):
        got = [tuple(r) for r in bucket_pairs(m.transform(v), 0.7, block).collect()]
        assert set(got) == want and len(got) == len(want) > 10
