"""Second review, F16: random vectors for the labels of the vectors."""

import os

import duckdb

from longweave.plans import registry

registry.everything()


def test_centroid_random_start_reads_embeddings(spark, sf):
    got = registry.QUERIES["centroid_random_start"](spark, sf)
    assert "embeddings" in registry.ORACLES["centroid_random_start"]
    assert any("embeddings" in f for f in got.inputFiles())
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    clean = lambda r: tuple("" if x is None else f"{x:.5f}" if isinstance(x, float) else str(x) for x in r)
    rows = sorted(map(clean, got.collect()))
    assert rows and rows == sorted(clean(r) for r in c.sql(registry.ORACLES["centroid_random_start"]).select(*got.columns).fetchall())
