"""Second review, F10: positions stay in tiles until they have met their paragraphs."""

import duckdb

from longweave.plans import registry

registry.everything()


def test_long_pages_meet_paragraphs_by_tiles(spark, tmp_path):
    import re

    pages = [(k, "".join(f"<p>{'w ' * (n * (k + 1) % 331)}</p>" for n in range(1, 40))) for k in range(4)] + [(9, ""), (10, None)]
    spark.createDataFrame(pages, "page_id long, html string").coalesce(1).write.parquet(f"{tmp_path}/pages.parquet")
    got = registry.QUERIES["join_range_paras"](spark, str(tmp_path))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert re.search(r"Generate explode[^\n]*\n(?:[^\n]*Project[^\n]*\n)*[^\n]*Join", plan), "positions must be made after the join"
    c = duckdb.connect()
    c.sql(f"create view pages as select * from '{tmp_path}/pages.parquet/*.parquet'")
    want = c.sql(registry.ORACLES["join_range_paras"]).select(*got.columns).fetchall()
    assert want and sorted(map(tuple, got.collect())) == sorted(want)
