"""Structured Streaming over events: windows, sessions, joins, duplicates, late rows, and the online bank."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.plans.registry import query
from longweave.session import load
from longweave.sources.tables import scratch, stream


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what there is and return its sink: a table of Parquet for append and complete (the last result), else
    rows in memory."""
    spark, name = df.sparkSession, f"sink_{uuid.uuid4().hex}"
    point = scratch(spark, "stream")
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{point}/out").option("checkpointLocation", f"{point}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{point}/out")
    if mode == "complete":  # each batch gives the whole result: two folders by turns, written by the executors
        last = []

        def put(rows: DataFrame, batch: int) -> None:
            rows.write.mode("overwrite").parquet(f"{point}/out-{batch % 2}")
            last[:] = [batch]

        df.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{point}/log").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{point}/out-{last[0] % 2}") if last else spark.createDataFrame([], df.schema)
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{point}/log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def events(spark: SparkSession, sf: str) -> DataFrame:
    load(spark, sf, "nation")
    return stream(spark, f"{sf}/events.parquet")


NTZ = lambda c: F.col(c).cast("timestamp_ntz")


@query("stream_tumbling", "select event_type, date_trunc('hour', ts) as start, count(*) as n, round(sum(value), 4) as v from events group by 1, 2")
def stream_tumbling(spark, sf):
    e = events(spark, sf).groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("v"))
    return drain(e, "complete").select("event_type", F.col("w.start").cast("timestamp_ntz").alias("start"), "n", F.round("v", 4).alias("v"))


@query("stream_sliding", "select s as start, count(*) as n from (select unnest([time_bucket(interval 30 minute, ts), time_bucket(interval 30 minute, ts) - interval 30 minute]) as s from events) group by 1")
def stream_sliding(spark, sf):
    e = events(spark, sf).groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"))
    return drain(e, "complete").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_session", """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end as k from events),
  s as (select *, sum(k) over (partition by user_id order by ts) as sid from g) select user_id, min(ts) as start, count(*) as n from s group by user_id, sid""")
def stream_session(spark, sf):
    """All sessions are the result, so no watermark drops rows of a later file; RocksDB holds them outside the heap."""
    e = events(spark, sf).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    key, rocks = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    before = spark.conf.get(key)
    spark.conf.set(key, rocks)
    try:
        done = drain(e, "complete")
    finally:
        spark.conf.set(key, before)
    return done.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_dedup", "select event_type, count(*) as n from events group by 1")
def stream_dedup(spark, sf):
    """Each event arrives twice; one of each stays, with state bounded by the watermark."""
    e = events(spark, sf).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    once = drain(e.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"))
    return once.groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_static_join", "select c_mktsegment, count(*) as n from events join customer on user_id = c_custkey group by 1")
def stream_static_join(spark, sf):
    c = load(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    e = events(spark, sf).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))
    return drain(e, "complete")


@query("stream_stream_join", "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts > c.ts and p.ts <= c.ts + interval 30 minute")
def stream_stream_join(spark, sf):
    c = events(spark, sf).filter("event_type = 'click'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("cts"))
    p = events(spark, sf).filter("event_type = 'purchase'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pts"))
    j = c.join(p, F.expr("cu = pu and pts > cts and pts <= cts + interval 30 minutes"))
    return drain(j.select("click_id", "purchase_id"))


@query("stream_late_drop", "select start, n from (select date_trunc('day', ts)::timestamp as start, count(*) as n from events group by 1) where start + interval 1 day <= (select max(ts) from events) - interval 1 hour")
def stream_late_drop(spark, sf):
    """The last file repeats the first with times a week back: rows behind the watermark are dropped.  The one between, the
    newest event again, lets the watermark take effect; its day is still open at the end."""
    path = scratch(spark, "late")
    e = load(spark, sf, "events")
    e.coalesce(1).write.parquet(f"{path}/k=1")
    e.orderBy(F.desc("ts")).limit(1).coalesce(1).write.parquet(f"{path}/k=2")
    e.withColumn("ts", F.expr("ts - interval 7 days")).coalesce(1).write.parquet(f"{path}/k=3")
    s = spark.readStream.schema(e.schema.add("k", "integer")).option("maxFilesPerTrigger", 1).option("basePath", path).parquet(path)
    s = s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    return drain(s.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_state_totals", "select user_id, count(*) as n, round(sum(value), 4) as total from events group by 1")
def stream_state_totals(spark, sf):
    """A state of its own for each user: number and sum of what came so far, given out after each batch."""
    import pandas as pd

    def add(key, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    e = events(spark, sf).select("user_id", "value")
    kind = dict(e.dtypes)["user_id"]
    held = e.groupBy("user_id").applyInPandasWithState(add, f"user_id {kind}, n long, total double", "n long, total double", "update", "NoTimeout")
    return drain(held, "update").groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max_by("total", "n"), 4).alias("total"))


@query("stream_bank", "select event_id as arrival, round(value, 6) as v0, hour(ts)::double as v1 from events order by event_id desc limit 1000")
def stream_bank(spark, sf):
    """The bank kept by a stream: each micro-batch writes its own folder (idempotent by batch id), reads take the newest."""
    from longweave.operators.bank import MemoryBank

    path = scratch(spark, "bank")
    bank = MemoryBank(spark, path, cap=1000)
    states = events(spark, sf).select(F.col("event_id").alias("arrival"), F.array(F.col("value"), F.hour("ts").cast("double")).alias("vec"))
    states.writeStream.foreachBatch(lambda df, k: bank.push(df, k)).option("checkpointLocation", f"{path}-log").trigger(availableNow=True).start().awaitTermination()
    return bank.read().select("arrival", F.round(F.col("vec")[0], 6).alias("v0"), F.col("vec")[1].alias("v1"))


@query("w_stream_refresh")
def w_stream_refresh(spark, sf):
    """The refresh loop online: events come in four files; each batch is pushed, what the bank no longer holds evicted,
    centroids are fitted after each second batch, and the batch's events get labels by the newest ones."""
    import numpy as np

    from longweave.functions import kernels as K
    from longweave.operators.bank import MemoryBank
    from longweave.operators.refresh import Refresh, fit

    path = scratch(spark, "stream-refresh")
    e = load(spark, sf, "events")
    last = (e.agg(F.max("event_id")).first()[0] or 0) + 1
    for k in range(4):
        e.filter(F.expr(f"event_id * 4 div {last} = {k}")).coalesce(1).write.parquet(f"{path}/in/k={k}")
    bank, how = MemoryBank(spark, f"{path}/bank", 5000, size="n"), Refresh(cap=5000, steps=3)
    now = {"c": np.random.default_rng(5).normal(size=(4, 3)) * 5, "fits": 0}

    def step(df, batch):
        rows = df.groupBy("user_id").agg(F.max("event_id").alias("seq_id"), F.count("*").alias("n"), F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("event_id", "vec"))), lambda x: x["vec"])).alias("flat"))
        bank.push(rows.drop("user_id"), batch + 1)  # a user's events are one sequence
        bank.evict()
        if (batch + 1) % 2 == 0:
            now["c"], now["fits"] = fit(bank.read(), now["c"], how), now["fits"] + 1
        ordered = now["c"][K.chain_order(now["c"])]
        fits = now["fits"]

        def label(batches):
            import pyarrow as pa

            for b in batches:
                x = np.array(b.column(1).to_pylist(), dtype=float).reshape(b.num_rows, -1)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(K.assign(x, ordered) if len(x) else [], pa.int32()), pa.array([fits] * b.num_rows, pa.int32())], ["event_id", "cluster", "fits"])

        df.select("event_id", "vec").mapInArrow(label, "event_id long, cluster int, fits int").write.mode("overwrite").parquet(f"{path}/out/batch={batch}")

    s = spark.readStream.schema(e.schema.add("k", "integer")).option("maxFilesPerTrigger", 1).option("basePath", f"{path}/in").parquet(f"{path}/in")
    states = s.select("event_id", "user_id", F.array(F.coalesce("value", F.lit(0.0)).cast("double"), F.hour("ts").cast("double"), F.dayofweek("ts").cast("double")).alias("vec"))
    states.writeStream.foreachBatch(step).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/out").groupBy("batch", "fits", "cluster").agg(F.count("*").alias("n"))
