"""Second review, F17: recursion over the orders."""

import os

import duckdb

from longweave.plans import registry

registry.everything()


def test_cte_recursive_reads_orders(spark, sf):
    got = registry.QUERIES["cte_recursive"](spark, sf)
    assert "orders" in registry.ORACLES["cte_recursive"]
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    clean = lambda r: tuple("" if x is None else f"{x:.5f}" if isinstance(x, float) else str(x) for x in r)
    rows = sorted(map(clean, got.collect()))
    assert rows and rows == sorted(clean(r) for r in c.sql(registry.ORACLES["cte_recursive"]).select(*got.columns).fetchall())
