"""Second review, F13: equal balances."""

import duckdb

from longweave.plans import registry

registry.everything()


def put(df, folder, name):
    df.coalesce(1).write.mode("overwrite").parquet(f"{folder}/{name}.parquet")


def test_argmax_takes_the_first_of_equal_balances(spark, tmp_path):
    rows = [(k, k % 2, 5.0 if k < 6 else None) for k in range(8)] + [(9, 1, 7.0), (10, 1, 7.0)]
    put(spark.createDataFrame(rows, "c_custkey long, c_nationkey int, c_acctbal double"), tmp_path, "customer")
    got = {r["c_nationkey"]: (r["richest"], r["poorest"]) for r in registry.QUERIES["agg_argmax"](spark, str(tmp_path)).collect()}
    c = duckdb.connect()
    c.sql(f"create view customer as select * from '{tmp_path}/customer.parquet/*.parquet'")
    assert got == {0: (0, 0), 1: (9, 1)} == {n: (a, b) for n, a, b in c.sql(registry.ORACLES["agg_argmax"]).fetchall()}
