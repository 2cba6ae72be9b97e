"""Relational operators around the methods: scans, joins, aggregates, windows, sets, strings, arrays, maps."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from longweave.functions.text import normal_answer, paragraphs
from longweave.functions.vectors import cosine, doubles
from longweave.operators import clusters as C
from longweave.plans import sqltext as S
from longweave.plans.method_queries import GOLD, PARAS, doc_tokens, gold_pairs, page_paras, vec_chain, vec_states
from longweave.plans.registry import query
from longweave.session import load, persist_cut

R6 = lambda c: F.round(c, 6)
LI_KEY = ["l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber"]


@query("scan_prune_filter", "select l_orderkey, l_linenumber, l_extendedprice, l_discount from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_discount between 0.05 and 0.07")
def scan_prune_filter(spark, sf):
    li = load(spark, sf, "lineitem")
    return li.filter((F.col("l_shipdate") >= F.expr("timestamp_ntz'1995-01-01'")) & (F.col("l_shipdate") < F.expr("timestamp_ntz'1996-01-01'")) & F.col("l_discount").between(0.05, 0.07)).select("l_orderkey", "l_linenumber", "l_extendedprice", "l_discount")


@query("scan_partitioned_lang", "select source, count(*) as n, sum(n_chars)::bigint as chars from documents where lang = 'en' group by source")
def scan_partitioned_lang(spark, sf):
    """Written by language once, then a filter on the folder's name reads one language only."""
    from longweave.sources.tables import scratch

    path = scratch(spark, "by-lang")
    load(spark, sf, "documents").write.mode("overwrite").partitionBy("lang").parquet(path)
    return spark.read.parquet(path).filter("lang = 'en'").groupBy("source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("scan_bucketed", "select quality::int as quality, count(*) as n, sum(n_chars)::bigint as chars from documents join labels using (doc_id) group by 1")
def scan_bucketed(spark, sf):
    """Two tables bucketed by doc_id: their join needs no exchange."""
    import uuid

    from longweave.sources.tables import bucketed

    tag = uuid.uuid4().hex
    d = bucketed(load(spark, sf, "documents").select("doc_id", "n_chars"), f"docs_{tag}", "doc_id", 8)
    b = bucketed(load(spark, sf, "labels").select("doc_id", "quality"), f"labels_{tag}", "doc_id", 8)
    return d.join(b.hint("merge"), "doc_id").groupBy(F.col("quality").cast("int").alias("quality")).agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("source_windows", """with x as (select max(vec_id) + 1 as x from embeddings), w as (select unnest(range((x + 223) // 224)) as k, x from x)
  select k::int as win, (k * 224)::int as lo, least(x, k * 224 + 256)::int as hi, count(vec_id) as n, round(sum(embedding[1]::double), 6) as first from w left join embeddings on vec_id >= k * 224 and vec_id < least(x, k * 224 + 256) group by k, x""")
def source_windows(spark, sf):
    """A data source of its own: the windows of the sequence of all vectors, read in parts; and what each window holds."""
    from longweave.sources.windows import Windows

    e = load(spark, sf, "embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("v"))
    spark.dataSource.register(Windows)
    rows = e.agg(F.max("vec_id")).first()[0]
    w = spark.read.format("windows").option("rows", 0 if rows is None else rows + 1).option("win", 256).option("stride", 224).load()
    last = F.floor(F.col("vec_id") / 224)  # a vector lies in this window, and in the one before if that reaches so far
    at = e.withColumn("win", F.explode(F.array(last.cast("int"), last.cast("int") - 1))).filter(F.col("vec_id") < F.col("win") * 224 + 256)
    held = at.groupBy("win").agg(F.count("vec_id").alias("n"), R6(F.sum("v")).alias("first"))
    return w.join(held, "win", "left").select("win", "lo", "hi", F.coalesce("n", F.lit(0)).alias("n"), "first")


@query("sink_overwrite_partition", "select 1 as layer, e::int as epoch, count(*) as n, round(sum(case when e = 2 then 2 else 1 end * embedding[1]::double), 6) as s from embeddings, (select unnest([1, 2]) as e) group by 1, 2")
def sink_overwrite_partition(spark, sf):
    """Snapshots by layer and epoch: writing an epoch again replaces its folder and no other."""
    from longweave.sources.tables import scratch

    path = scratch(spark, "snapshots")
    e = load(spark, sf, "embeddings").select(F.lit(1).alias("layer"), F.lit(1).alias("epoch"), F.col("embedding")[0].cast("double").alias("x"))
    put = lambda df, mode: df.write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("layer", "epoch").parquet(path)
    put(e, "append")
    put(e.withColumn("epoch", F.lit(2)), "append")
    put(e.withColumn("epoch", F.lit(2)).withColumn("x", F.col("x") * 2), "overwrite")
    return spark.read.parquet(path).groupBy("layer", "epoch").agg(F.count("*").alias("n"), R6(F.sum("x")).alias("s"))


@query("sql_surface", f"with {S.TOK} select seq_id, round(list_cosine_similarity({S.hash_vec('a')}, {S.hash_vec('b')}), 6) + 0.0 as sim, k as windows from (select seq_id, t[1] as a, t[len(t)] as b, (len(t) + 223) // 224 as k from tl where len(t) > 0)")
def sql_surface(spark, sf):
    """The methods from SQL: views of the tables, functions for states, similarity and windows."""
    from longweave.sources.functions import register, views

    register(spark)
    views(spark, sf, ["documents"])
    return spark.sql("""
        with t as (select doc_id as seq_id, filter(split(trim(lower(coalesce(text, ''))), '\\\\s+'), x -> x <> '') as t from documents_v),
        w as (select seq_id, t[0] as a, t[size(t) - 1] as b, cast(ceil(size(t) / 224) as bigint) as windows from t where size(t) > 0)
        select seq_id, round(cosine_to(token_state(a), token_state(b)), 6) + 0.0 as sim, windows from w""")


@query("roundtrip_csv_json_orc", "select f as format, count(*) as n, sum(n_nationkey)::bigint as keys, sum(length(n_name))::bigint as name_chars from nation, (select unnest(['csv', 'json', 'orc']) as f) group by f")
def roundtrip_csv_json_orc(spark, sf):
    from longweave.sources.tables import roundtrip

    n, out = load(spark, sf, "nation"), None
    for f in ("csv", "json", "orc"):
        part = roundtrip(n, f).select(F.lit(f).alias("format"), "n_nationkey", "n_name")
        out = part if out is None else out.unionByName(part)
    return out.groupBy("format").agg(F.count("*").alias("n"), F.sum("n_nationkey").alias("keys"), F.sum(F.length("n_name")).alias("name_chars"))


@query("proj_struct", "select doc_id, lang || ':' || source as tag, n_chars * 2 as twice from documents")
def proj_struct(spark, sf):
    d = load(spark, sf, "documents").withColumn("s", F.struct("lang", "source"))
    return d.select("doc_id", F.concat_ws(":", "s.lang", "s.source").alias("tag"), (F.col("n_chars") * 2).alias("twice"))


@query("filter_rlike", r"select doc_id from documents where regexp_matches(text, '[0-9]{4}') and lang in ('en', 'de')")
def filter_rlike(spark, sf):
    return load(spark, sf, "documents").filter(F.col("text").rlike("[0-9]{4}") & F.col("lang").isin("en", "de")).select("doc_id")


@query("distinct_texts", "select lang, count(*) as n from (select distinct lang, text from documents) group by lang")
def distinct_texts(spark, sf):
    return load(spark, sf, "documents").dropDuplicates(["lang", "text"]).groupBy("lang").agg(F.count("*").alias("n"))


@query("join_broadcast_star", """select r_name, year(o_orderdate)::int as y, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey
  join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2""")  # fmt: skip
def join_broadcast_star(spark, sf):
    g = lambda t: load(spark, sf, t)
    nations = g("nation").join(F.broadcast(g("region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows at any scale
    j = g("lineitem").join(g("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(g("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("r_name", F.year("o_orderdate").alias("y")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("join_merge_orders", "select o_orderpriority, count(*) as n, round(sum(l_quantity), 2) as q from orders join lineitem on o_orderkey = l_orderkey group by 1")
def join_merge_orders(spark, sf):
    j = load(spark, sf, "orders").hint("merge").join(load(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"))


@query("join_shuffled_hash", "select o_orderstatus, count(*) as n from orders join lineitem on o_orderkey = l_orderkey where l_quantity > 25 group by 1")
def join_shuffled_hash(spark, sf):
    j = load(spark, sf, "lineitem").filter("l_quantity > 25").join(load(spark, sf, "orders").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("join_theta_contains", f"select doc_id, item_id, instr(d.text, b.text)::int as at from {GOLD}")
def join_theta_contains(spark, sf):
    return gold_pairs(spark, sf).select("doc_id", "item_id", F.expr("instr(text, passage)").alias("at"))


@query("join_range_paras", rf"""with {PARAS}, n as (select page_id, para_id, len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) + 1 as k from pa),
  b as (select *, sum(k) over (partition by page_id order by para_id) - k as lo from n) select page_id as seq_id, para_id, count(*) as tokens, min(pos)::int as first from (select page_id, para_id, unnest(range(lo::bigint, (lo + k)::bigint)) as pos from b) group by 1, 2""")
def join_range_paras(spark, sf):
    """Token positions to the paragraphs [lo, hi) that hold them, sequence by sequence."""
    from longweave.functions.text import words

    p = page_paras(spark, sf).select("seq_id", "para_id", (F.size(words("text")) + 1).alias("k"))
    hi = F.sum("k").over(Window.partitionBy("seq_id").orderBy("para_id"))
    p = p.withColumn("hi", hi).withColumn("lo", F.col("hi") - F.col("k"))
    # tiles of 64 positions meet the paragraphs of their own bucket; only then a tile gives its positions
    x = p.groupBy("seq_id").agg(F.sum("k").alias("x"))
    t = x.select("seq_id", "x", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("x") - 1) / 64))).alias("b"))
    cut = p.withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") / 64), F.floor((F.col("hi") - 1) / 64))))
    tile = F.sequence(F.col("b") * 64, F.least(F.col("b") * 64 + 63, F.col("x") - 1))
    j = t.join(cut, ["seq_id", "b"]).select("seq_id", "para_id", "lo", "hi", F.explode(tile).alias("pos")).filter((F.col("pos") >= F.col("lo")) & (F.col("pos") < F.col("hi")))
    return j.groupBy("seq_id", "para_id").agg(F.count("*").alias("tokens"), F.min("pos").cast("int").alias("first"))


@query("join_asof_signup", """select p.event_id, s.event_id as signup_id from (select * from events where event_type = 'purchase') p asof left join (select * from events where event_type = 'signup') s on p.user_id = s.user_id and p.ts > s.ts""")
def join_asof_signup(spark, sf):
    """As-of by one pass: union, order, carry the last signup forward.  No pairs are made."""
    e = load(spark, sf, "events").filter(F.col("event_type").isin("purchase", "signup"))
    before = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, -1)
    s = F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(before)
    return e.withColumn("signup_id", s).filter("event_type = 'purchase'").select("event_id", "signup_id")


@query("join_interval_click", "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts > c.ts and p.ts <= c.ts + interval 30 minute")
def join_interval_click(spark, sf):
    """Buckets of 30 minutes make it an equality join: a purchase meets clicks of its own bucket and the one before."""
    e = load(spark, sf, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 1800).alias("b"))
    c = e.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("cts"), "b")
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("pts"), F.explode(F.array(F.col("b"), F.col("b") - 1)).alias("b"))
    return c.join(p, ["user_id", "b"]).filter("pts > cts and pts <= cts + interval 30 minutes").select("click_id", "purchase_id")


@query("join_semi_gold", f"select distinct doc_id from {GOLD}")
def join_semi_gold(spark, sf):
    return load(spark, sf, "documents").join(gold_pairs(spark, sf).select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id")


@query("join_anti_unlabelled", "select doc_id from documents where doc_id not in (select doc_id from labels)")
def join_anti_unlabelled(spark, sf):
    return load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id", "left_anti").select("doc_id")


@query("join_outer_all", "select n_name, s.n as suppliers, c.n as customers from nation left join (select s_nationkey, count(*) as n from supplier group by 1) s on n_nationkey = s_nationkey full join (select c_nationkey, count(*) as n from customer where c_acctbal > 9000 group by 1) c on n_nationkey = c_nationkey")
def join_outer_all(spark, sf):
    n = load(spark, sf, "nation")
    s = load(spark, sf, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("suppliers"))
    c = load(spark, sf, "customer").filter("c_acctbal > 9000").groupBy("c_nationkey").agg(F.count("*").alias("customers"))
    return n.join(s, F.col("n_nationkey") == F.col("s_nationkey"), "left").join(c, F.col("n_nationkey") == F.col("c_nationkey"), "full").select("n_name", "suppliers", "customers")


@query("join_lateral_top", "select n_name, x.c_custkey, x.c_acctbal from nation, lateral (select c_custkey, c_acctbal from customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2) x")
def join_lateral_top(spark, sf):
    load(spark, sf, "nation").createOrReplaceTempView("nation_v")
    load(spark, sf, "customer").createOrReplaceTempView("customer_v")
    best = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    c = spark.table("customer_v").withColumn("r", F.row_number().over(best)).filter("r <= 2")
    return spark.table("nation_v").join(c, F.col("n_nationkey") == F.col("c_nationkey")).select("n_name", "c_custkey", "c_acctbal")


@query("join_self_parts", "select a.p_brand, count(*) as pairs from part a join part b on a.p_brand = b.p_brand and a.p_size = b.p_size and a.p_partkey < b.p_partkey group by 1")
def join_self_parts(spark, sf):
    """Pairs of a group counted from its size, not made."""
    n = load(spark, sf, "part").groupBy("p_brand", "p_size").agg(F.count("*").alias("n"))
    return n.withColumn("p", (F.col("n") * (F.col("n") - 1) / 2).cast("long")).groupBy("p_brand").agg(F.sum("p").alias("pairs")).filter("pairs > 0")


@query("join_cross_regions", "select a.r_name as a, b.r_name as b from region a, region b where a.r_regionkey < b.r_regionkey")
def join_cross_regions(spark, sf):
    r = load(spark, sf, "region")  # five rows at any scale
    return r.select(F.col("r_name").alias("a"), F.col("r_regionkey").alias("ka")).crossJoin(r.select(F.col("r_name").alias("b"), F.col("r_regionkey").alias("kb"))).filter("ka < kb").select("a", "b")


@query("agg_basic", "select l_returnflag, l_linestatus, sum(l_quantity) as sum_qty, round(avg(l_extendedprice), 4) as avg_price, min(l_discount) as lo, max(l_tax) as hi, count(*) as n from lineitem group by 1, 2")
def agg_basic(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("sum_qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi"), F.count("*").alias("n"))


@query("agg_sorted_lists", "select n_regionkey, array_to_string(list(n_name order by n_nationkey), ',') as names from nation group by 1")
def agg_sorted_lists(spark, sf):
    items = F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name")))
    return load(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.transform(items, lambda x: x["n_name"]), ",").alias("names"))


@query("agg_multi_distinct", "select event_type, count(distinct user_id) as users, count(distinct ts::date) as days from events group by 1")
def agg_multi_distinct(spark, sf):
    return load(spark, sf, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.to_date("ts")).alias("days"))


@query("agg_rollup_lang_source", "select lang, source, grouping(lang)::int * 2 + grouping(source)::int as g, count(*) as n, sum(n_chars)::bigint as chars from documents group by rollup (lang, source)")
def agg_rollup_lang_source(spark, sf):
    return load(spark, sf, "documents").rollup("lang", "source").agg(F.grouping_id().cast("int").alias("g"), F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("agg_cube_flags", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def agg_cube_flags(spark, sf):
    return load(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark, sf):
    o = load(spark, sf, "orders")
    return o.groupingSets([[o["o_orderstatus"]], [o["o_orderpriority"]], []], o["o_orderstatus"], o["o_orderpriority"]).agg(F.count("*").alias("n"))


@query("agg_stats", "select l_returnflag, round(stddev_samp(l_quantity), 6) as sd, round(corr(l_quantity, l_extendedprice), 6) as r, count(*) filter (where l_discount > 0.05) as many, bool_and(l_tax >= 0) as ok from lineitem group by 1")
def agg_stats(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(R6(F.stddev("l_quantity")).alias("sd"), R6(F.corr("l_quantity", "l_extendedprice")).alias("r"), F.count_if(F.col("l_discount") > 0.05).alias("many"), F.bool_and(F.col("l_tax") >= 0).alias("ok"))


@query("agg_argmax", "select c_nationkey, max_by(c_custkey, c_acctbal) as richest, min_by(c_custkey, c_acctbal) as poorest from customer group by 1")
def agg_argmax(spark, sf):
    """Of equal balances the smallest key counts, which is the first row that the SQL meets; rows without a balance don't."""
    known = F.col("c_acctbal").isNotNull() & F.col("c_custkey").isNotNull()
    by = lambda key: F.when(known, F.struct("c_acctbal", key))
    return load(spark, sf, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", by(F.bitwise_not("c_custkey"))).alias("richest"), F.min_by("c_custkey", by("c_custkey")).alias("poorest"))


@query("agg_median_len", "select lang, median(n_chars) as mid, quantile_cont(n_chars, 0.9) as p90, max(n_chars) as longest from documents group by 1")
def agg_median_len(spark, sf):
    return load(spark, sf, "documents").groupBy("lang").agg(F.median("n_chars").alias("mid"), F.percentile("n_chars", 0.9).alias("p90"), F.max("n_chars").alias("longest"))


@query("agg_approx_distinct", f"with {S.TOK}, l as (select lang, count(distinct tok) as exact from tok join documents on doc_id = seq_id group by 1) select lang, exact, true as within from l")
def agg_approx_distinct(spark, sf):
    """HyperLogLog sketches per language, merged over sources; and the exact number beside it."""
    t = doc_tokens(spark, sf).join(load(spark, sf, "documents").select(F.col("doc_id").alias("seq_id"), "lang", "source"), "seq_id")
    part = t.groupBy("lang", "source").agg(F.hll_sketch_agg("tok").alias("k"))
    near = part.groupBy("lang").agg(F.hll_sketch_estimate(F.hll_union_agg("k")).alias("near"))
    both = near.join(t.groupBy("lang").agg(F.count_distinct("tok").alias("exact")), "lang")
    return both.select("lang", "exact", (F.abs(F.col("near") - F.col("exact")) <= 0.06 * F.col("exact") + 1).alias("within"))


@query("agg_sketch_quantile", "select l_returnflag, true as within from lineitem group by 1")
def agg_sketch_quantile(spark, sf):
    """The sketch's quantiles have the ranks they claim, within a thousandth of all rows."""
    li = load(spark, sf, "lineitem").select("l_returnflag", "l_extendedprice")
    q = li.groupBy("l_returnflag").agg(F.approx_percentile("l_extendedprice", [0.5, 0.9], 10_000).alias("q"), F.count("*").alias("n"))
    below = li.join(F.broadcast(q), "l_returnflag")  # one row for each flag
    at = lambda k: [F.count_if(F.col("l_extendedprice") < F.col("q")[k]).alias(f"lt{k}"), F.count_if(F.col("l_extendedprice") <= F.col("q")[k]).alias(f"le{k}")]
    rank = below.groupBy("l_returnflag").agg(F.first("n").alias("n"), *at(0), *at(1))
    ok = lambda k, p: (F.col(f"lt{k}") <= (p + 0.001) * F.col("n") + 1) & (F.col(f"le{k}") >= (p - 0.001) * F.col("n") - 1)
    return rank.select("l_returnflag", (ok(0, 0.5) & ok(1, 0.9)).alias("within"))


@query("agg_vector_mean", f"with {S.CENT} select cid as label, (j - 1)::int as j, round(v, 6) + 0.0 as v from ce")
def agg_vector_mean(spark, sf):
    m = C.label_means(load(spark, sf, "embeddings"))
    return m.select(F.col("cid").alias("label"), F.posexplode("vec").alias("j", "v")).withColumn("v", R6("v") + 0.0)


@query("pivot_status", "select o_orderpriority, count(*) filter (where o_orderstatus = 'F') as \"F\", count(*) filter (where o_orderstatus = 'O') as \"O\", count(*) filter (where o_orderstatus = 'P') as \"P\" from orders group by 1")
def pivot_status(spark, sf):
    p = load(spark, sf, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey"))
    return p.fillna(0)


@query("unpivot_nums", "select s_suppkey, k as what, v::double as v from (select s_suppkey, unnest(['nation', 'balance']) as k, unnest([s_nationkey::double, s_acctbal]) as v from supplier)")
def unpivot_nums(spark, sf):
    s = load(spark, sf, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance"))
    return s.unpivot("s_suppkey", ["nation", "balance"], "what", "v")


@query("win_ranking", "select c_custkey, (rank() over w)::int as r, (dense_rank() over w)::int as d, (ntile(4) over (partition by c_nationkey order by c_acctbal desc, c_custkey))::int as q, round(percent_rank() over w, 6) as p, round(cume_dist() over w, 6) as c from customer window w as (partition by c_nationkey order by c_acctbal desc)")
def win_ranking(spark, sf):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    u = w.orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(u).alias("q"), R6(F.percent_rank().over(w)).alias("p"), R6(F.cume_dist().over(w)).alias("c"))


LI_W = "over (partition by l_suppkey order by l_shipdate, l_orderkey, l_linenumber"


@query("win_lag_lead", f"select l_suppkey, l_orderkey, l_linenumber, l_shipdate, lag(l_quantity) {LI_W}) as before, lead(l_quantity) {LI_W}) as after, first_value(l_quantity) {LI_W}) as first, nth_value(l_quantity, 2) {LI_W}) as second from lineitem")
def win_lag_lead(spark, sf):
    w = Window.partitionBy("l_suppkey").orderBy(*LI_KEY[1:])
    return load(spark, sf, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_shipdate", F.lag("l_quantity").over(w).alias("before"), F.lead("l_quantity").over(w).alias("after"), F.first("l_quantity").over(w).alias("first"), F.nth_value("l_quantity", 2).over(w).alias("second"))


@query("win_running_sum", f"select l_suppkey, l_orderkey, l_linenumber, l_shipdate, sum(l_quantity) {LI_W} rows unbounded preceding) as running from lineitem")
def win_running_sum(spark, sf):
    w = Window.partitionBy("l_suppkey").orderBy(*LI_KEY[1:]).rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, sf, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", "l_shipdate", F.sum("l_quantity").over(w).alias("running"))


@query("win_moving_avg_range", "select event_id, round(avg(value) over (partition by event_type order by ts range between interval 1 hour preceding and current row), 6) as m from events")
def win_moving_avg_range(spark, sf):
    w = Window.partitionBy("event_type").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return load(spark, sf, "events").select("event_id", R6(F.avg("value").over(w)).alias("m"))


@query("win_islands", "with d as (select distinct user_id, ts::date as day from events), g as (select *, day - (row_number() over (partition by user_id order by day))::int as k from d) select user_id, min(day)::varchar as first_day, count(*) as days from g group by user_id, k")
def win_islands(spark, sf):
    d = load(spark, sf, "events").select("user_id", F.to_date("ts").alias("day")).distinct()
    g = d.withColumn("k", F.date_sub("day", F.row_number().over(Window.partitionBy("user_id").orderBy("day"))))
    return g.groupBy("user_id", "k").agg(F.min("day").cast("string").alias("first_day"), F.count("*").alias("days")).drop("k")


@query("topk_global", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")
def topk_global(spark, sf):
    return load(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("topk_per_group", "select o_orderpriority, o_orderkey from (select *, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as r from orders) where r <= 3")
def topk_per_group(spark, sf):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, sf, "orders").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("o_orderpriority", "o_orderkey")


@query("sort_multi", "select p_partkey, p_brand, p_size from part order by p_brand, p_size desc, p_partkey")
def sort_multi(spark, sf):
    return load(spark, sf, "part").select("p_partkey", "p_brand", "p_size").orderBy("p_brand", F.desc("p_size"), "p_partkey")


@query("sample_hash", "select doc_id from documents where ('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 10 = 3")
def sample_hash(spark, sf):
    """The sampling operator: a stable tenth by hash."""
    return load(spark, sf, "documents").filter(F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 10 == 3).select("doc_id")


@query("set_union", "select k, count(*) as n from (select s_nationkey as k from supplier union all select c_nationkey from customer) group by k")
def set_union(spark, sf):
    a, b = load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k")), load(spark, sf, "customer").select(F.col("c_nationkey").alias("k"))
    return a.unionByName(b).groupBy("k").agg(F.count("*").alias("n"))


@query("set_intersect_all", "select k, count(*) as n from (select s_nationkey as k from supplier intersect all select c_nationkey from customer) group by k")
def set_intersect_all(spark, sf):
    a, b = load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k")), load(spark, sf, "customer").select(F.col("c_nationkey").alias("k"))
    return a.intersectAll(b).groupBy("k").agg(F.count("*").alias("n"))


@query("set_except_all", "select k, count(*) as n from (select c_nationkey as k from customer except all select s_nationkey from supplier) group by k")
def set_except_all(spark, sf):
    a, b = load(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), load(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))
    return a.exceptAll(b).groupBy("k").agg(F.count("*").alias("n"))


@query("str_normalise", r"select item_id, array_to_string(list_filter(regexp_split_to_array(regexp_replace(lower(text), '[!-/:-@\[-`{-~]', '', 'g'), '\s+'), lambda w: w not in ('', 'a', 'an', 'the')), ' ') as norm from benchmark")
def str_normalise(spark, sf):
    return load(spark, sf, "benchmark").select("item_id", normal_answer("text").alias("norm"))


@query("str_regex", r"select page_id, regexp_extract(url, '^https?://([^/]+)', 1) as host, length(url)::int as n, instr(url, '/')::int as slash, levenshtein(substr(url, 1, 20), 'https://example.org')::int as far, md5(url) as h from pages")
def str_regex(spark, sf):
    return load(spark, sf, "pages").select("page_id", F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), F.length("url").alias("n"), F.instr("url", "/").alias("slash"), F.levenshtein(F.substring("url", 1, 20), F.lit("https://example.org")).alias("far"), F.md5("url").alias("h"))


@query("html_paragraphs", f"with {PARAS} select page_id, para_id, text from pa")
def html_paragraphs(spark, sf):
    return load(spark, sf, "pages").select("page_id", F.posexplode(paragraphs("html")).alias("para_id", "text"))


@query("date_buckets", "select year(o_orderdate)::int as y, month(o_orderdate)::int as m, count(*) as n, max(date_diff('day', date '1992-01-01', o_orderdate::date))::int as last_day from orders group by 1, 2")
def date_buckets(spark, sf):
    return load(spark, sf, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))).alias("last_day"))


@query("math_mix", "select p_partkey, round(sqrt(p_retailprice), 6) as root, round(ln(p_retailprice), 6) as lg, round(exp(p_size / 50.0), 6) as e, ceil(p_retailprice)::bigint as up, floor(p_retailprice)::bigint as down, greatest(p_size, 25)::int as g, (p_size % 7)::int as m from part")
def math_mix(spark, sf):
    p = F.col("p_retailprice")
    return load(spark, sf, "part").select("p_partkey", R6(F.sqrt(p)).alias("root"), R6(F.ln(p)).alias("lg"), R6(F.exp(F.col("p_size") / 50.0)).alias("e"), F.ceil(p).alias("up"), F.floor(p).alias("down"), F.greatest("p_size", F.lit(25)).alias("g"), F.pmod("p_size", F.lit(7)).alias("m"))


@query("cond_nulls", "select d.doc_id, coalesce(l.quality, -1)::int as q, nullif(l.toxic, 0)::int as t, case when l.quality is null then 'none' when l.quality = 1 then 'good' else 'bad' end as k from documents d left join labels l using (doc_id)")
def cond_nulls(spark, sf):
    j = load(spark, sf, "documents").select("doc_id").join(load(spark, sf, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.nullif("toxic", F.lit(0)).alias("t"), F.when(F.col("quality").isNull(), "none").when(F.col("quality") == 1, "good").otherwise("bad").alias("k"))


@query("arr_hofs", "select vec_id, len(list_filter(embedding, lambda x: x > 0))::int as pos, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) as sq, round(list_max(embedding)::double, 6) as top, len(embedding[3:10])::int as cut from embeddings")
def arr_hofs(spark, sf):
    v = doubles("embedding")
    return load(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), R6(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x)).alias("sq"), R6(F.array_max("embedding").cast("double")).alias("top"), F.size(F.slice("embedding", 3, 8)).alias("cut"))


@query("vec_cosine_pairs", f"with {S.CENT} select a.cid as a, b.cid as b, round(list_cosine_similarity(a.vec, b.vec), 6) as sim from c a join c b on a.cid < b.cid")
def vec_cosine_pairs(spark, sf):
    c = C.label_means(load(spark, sf, "embeddings"))  # one row per label
    a, b = c.select(F.col("cid").alias("a"), F.col("vec").alias("va")), c.select(F.col("cid").alias("b"), F.col("vec").alias("vb"))
    return a.join(F.broadcast(b), F.col("a") < F.col("b")).select("a", "b", R6(cosine("va", "vb")).alias("sim"))


@query("map_histogram", "select user_id, array_to_string(list(event_type || '=' || n order by event_type), ',') as h from (select user_id, event_type, count(*) as n from events group by 1, 2) where n > 5 group by 1")
def map_histogram(spark, sf):
    n = load(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_filter(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))), lambda k, v: v > 5).alias("m")).filter(F.size("m") > 0)
    return m.select("user_id", F.array_join(F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",").alias("h"))


@query("json_props", "select event_type, sum((props->>'$.k')::int)::bigint as k, max((props->>'$.k')::int)::int as top from events group by 1")
def json_props(spark, sf):
    k = F.from_json("props", "k int")["k"]
    return load(spark, sf, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.max(k).alias("top"))


@query("sub_correlated", "select c_custkey from customer c where c_acctbal > (select avg(c_acctbal) * 1.5 from customer x where x.c_nationkey = c.c_nationkey)")
def sub_correlated(spark, sf):
    c = load(spark, sf, "customer")
    a = c.groupBy("c_nationkey").agg((F.avg("c_acctbal") * 1.5).alias("a"))
    return c.join(a, "c_nationkey").filter("c_acctbal > a").select("c_custkey")


@query("sub_exists", "select s_suppkey from supplier where exists (select 1 from lineitem where l_suppkey = s_suppkey and l_discount >= 0.1 and l_quantity > 45)")
def sub_exists(spark, sf):
    li = load(spark, sf, "lineitem").filter("l_discount >= 0.1 and l_quantity > 45")
    return load(spark, sf, "supplier").join(li, F.col("s_suppkey") == F.col("l_suppkey"), "left_semi").select("s_suppkey")


@query("cte_recursive", """with recursive y as (select year(o_orderdate)::int as y, count(*) as c, sum(o_custkey)::bigint as s from orders group by 1),
  t as (select y as n, c as f, s as g from y where y = (select min(y) from y) union all select t.n + 1, t.f + y.c, t.g + y.s from t join y on y.y = t.n + 1) select n, f, g from t""")
def cte_recursive(spark, sf):
    """Running totals of the orders by recursion, a year at each level."""
    load(spark, sf, "orders").createOrReplaceTempView("orders_v")
    # a row for each year, once; levels join these
    persist_cut(spark.sql("select year(o_orderdate) as y, count(*) as c, sum(o_custkey) as s from orders_v group by 1")).createOrReplaceTempView("years_v")
    return spark.sql("""with recursive t(n, f, g) as (select y, c, s from years_v where y = (select min(y) from years_v)
        union all select t.n + 1, t.f + years_v.c, t.g + years_v.s from t join years_v on years_v.y = t.n + 1) select n, f, g from t""")


@query("udf_arrow_cosine", f"{S.vectors_slice()} select vec_id, round(list_cosine_similarity(vec, (select vec from chain where ord = 0)), 6) as sim from asg")
def udf_arrow_cosine(spark, sf):
    from longweave.sources.functions import register

    register(spark)
    first = vec_chain(spark, sf).filter("ord = 0").first()["vec"]
    return vec_states(spark, sf).withColumn("q", F.array(*map(F.lit, first))).selectExpr("vec_id", "round(cosine_to(vec, q), 6) as sim")


@query("udaf_vector_mean", f"with {S.CENT} select cid as label, (j - 1)::int as j, round(v, 6) + 0.0 as v from ce")
def udaf_vector_mean(spark, sf):
    """By partial sums in Python per task, then a small sum: the shape of a user-defined aggregate."""
    import numpy as np
    import pyarrow as pa

    def partial(batches):
        total: dict[int, list] = {}
        for b in batches:
            label, v = b.column(0).to_numpy(), np.array(b.column(1).to_pylist(), dtype=np.float64)
            for k in np.unique(label) if len(label) else ():
                s = total.setdefault(int(k), [0, 0.0])
                s[0] += int((label == k).sum())
                s[1] = s[1] + v[label == k].sum(0)
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([s[0] for s in total.values()], pa.int64()), pa.array([s[1] for s in total.values()], pa.list_(pa.float64()))], ["label", "n", "s"])

    p = load(spark, sf, "embeddings").select("label", doubles("embedding")).mapInArrow(partial, "label int, n long, s array<double>")
    each = p.select("label", "n", F.posexplode("s").alias("j", "v")).groupBy("label", "j").agg((R6(F.sum("v") / F.sum("n")) + 0.0).alias("v"))
    return each


@query("udtf_windows", f"with {S.TOK} select seq_id, k::int as win, (k * 224)::int as lo, least(len(t), k * 224 + 256)::int as hi from (select *, unnest(range((len(t) + 223) // 224)) as k from tl where len(t) > 0)")
def udtf_windows(spark, sf):
    from longweave.sources.functions import register

    register(spark)
    doc_tokens(spark, sf).groupBy("seq_id").agg(F.count("*").cast("int").alias("x")).createOrReplaceTempView("lengths_v")
    return spark.sql("select l.seq_id, w.win, w.lo, w.hi from lengths_v l, lateral windows_of(l.x, 256, 224) w")


@query("grouped_arrow_blocks", f"{S.vectors_slice()}, b as (select vec_id, vec, srank // 32 as block from ranked), o as {S.attention('b', 'block', 'vec_id', 0.125)} select vec_id, {', '.join(f'round(o{j}, 6) + 0.0 as o{j}' for j in range(1, 5))} from o")
def grouped_arrow_blocks(spark, sf):
    """Blocks as groups of an Arrow function: a group is a block, so bounded."""
    import numpy as np
    import pyarrow as pa

    from longweave.functions.kernels import attention
    from longweave.plans.method_queries import vec_ranked

    def attend(t):
        v = attention(np.array(t["vec"].to_pylist()), scale=0.125)
        return pa.table({"vec_id": t["vec_id"], **{f"o{j + 1}": pa.array(np.round(v[:, j], 6) + 0.0) for j in range(4)}})

    b = C.chunk(vec_ranked(spark, sf), 32).select("seq_id", "block", "vec_id", "vec")
    return b.groupBy("seq_id", "block").applyInArrow(attend, "vec_id long, o1 double, o2 double, o3 double, o4 double")


@query("ml_kmeans_sizes")
def ml_kmeans_sizes(spark, sf):
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = load(spark, sf, "embeddings").select(array_to_vector(doubles("embedding")).alias("features"))
    return KMeans(k=10, seed=1, initMode="k-means||", distanceMeasure="cosine").fit(v).transform(v).groupBy("prediction").agg(F.count("*").alias("n"))


def pooled_quality(spark, sf):
    """(doc_id, held, p, label): logistic regression on mean states, fitted on the documents that are not held out."""
    import numpy as np
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector, vector_to_array

    from longweave.operators.fused import per_sequence, states_of
    from longweave.plans.method_queries import docs_packed

    def pool(seq, toks):
        x = states_of(toks, 8, 7) if toks else np.zeros((1, 8))
        return {"doc_id": seq, "x": [*x.mean(0), *x.std(0), float(np.log1p(len(toks))), len(set(toks)) / max(1, len(toks))]}

    d = per_sequence(docs_packed(spark, sf), pool, "doc_id long, x array<double>").join(load(spark, sf, "labels"), "doc_id")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 1
    d = persist_cut(d.select("doc_id", held.alias("held"), F.col("quality").cast("double").alias("label"), array_to_vector("x").alias("features")))  # the fit passes over it many times
    model = LogisticRegression(regParam=0.01).fit(d.filter("not held"))
    return model.transform(d).select("doc_id", "held", F.round(vector_to_array("probability")[1], 4).alias("p"), "label")


@query("ml_logreg_quality")
def ml_logreg_quality(spark, sf):
    return pooled_quality(spark, sf)


@query("ml_idf", f"with {S.TOK}, d as (select tok, count(distinct seq_id) as df from tok group by 1), n as (select count(*) as n from tl) select tok, df::bigint as df, round(ln((n + 1.0) / (df + 1.0)), 6) as idf from d, n where df >= ceil(0.05 * n)")
def ml_idf(spark, sf):
    """Words of at least a twentieth of the documents, by the library's counter, and their inverse document frequency."""
    from pyspark.ml.feature import IDF, CountVectorizer

    from longweave.plans.method_queries import docs_packed

    d = docs_packed(spark, sf)
    n = d.count()
    counter = CountVectorizer(inputCol="toks", outputCol="tf", minDF=float(-(-n // 20) or 1), vocabSize=1 << 18).fit(d)
    model = IDF(inputCol="tf", outputCol="v").fit(counter.transform(d))
    rows = [(w, int(k), float(x)) for w, k, x in zip(counter.vocabulary, model.docFreq, model.idf.toArray(), strict=True)]
    return spark.createDataFrame(rows, "tok string, df long, idf double").select("tok", "df", R6("idf").alias("idf"))


@query("lsh_join")
def lsh_join(spark, sf):
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = load(spark, sf, "embeddings").select("vec_id", array_to_vector(doubles("embedding")).alias("f"))
    m = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=0.5, numHashTables=3, seed=1).fit(v)
    return bucket_pairs(m.transform(v), 1.1)


def bucket_pairs(hashed, limit, block=8192):
    """(a, b, dist) of the rows (vec_id, f, h) with a < b that share a bucket of one of their hashes and are less than limit
    apart: what the model's own join gives, also where most rows share buckets.

    Rows are dealt to blocks and every two blocks meet once; products of matrices say which rows are near, the vectors of
    these how far apart they are.
    """
    import numpy as np
    import pyarrow as pa
    from pyspark.ml.functions import vector_to_array

    n, tables = hashed.agg(F.count("*"), F.max(F.size("h"))).first()
    blocks = max(1, -(-n // block))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    keys = F.array(*(vector_to_array(F.col("h")[k])[0] for k in range(tables or 0))).cast("array<double>")
    flat = hashed.select("vec_id", vector_to_array("f").alias("f"), keys.alias("h"), own.alias("own"))
    met = flat.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("x", F.least("own", "other")).withColumn("y", F.greatest("own", "other")).drop("other")

    def near(t):
        at, ids = t.column("own").to_numpy(), t.column("vec_id").to_numpy()
        x, y = t.column("x")[0].as_py(), t.column("y")[0].as_py()
        f, h = (np.concatenate([p.flatten().to_numpy() for p in t.column(c).chunks]).reshape(t.num_rows, -1) for c in ("f", "h"))
        one, two, norm, out = np.flatnonzero(at == x), np.flatnonzero(at == y), (f * f).sum(1), []
        out.append((ids[:0], ids[:0], norm[:0]))
        for lo in range(0, len(one), 256):
            i = one[lo : lo + 256]
            both = norm[i][:, None] + norm[two]
            p, q = np.nonzero(both - 2 * f[i] @ f[two].T < limit**2 + 1e-6 * (1 + both))
            p, q = i[p], two[q]
            for k in range(0, len(p), 65536):
                a, b = p[k : k + 65536], q[k : k + 65536]
                may = (h[a] == h[b]).any(1) & ((ids[a] < ids[b]) if x == y else (ids[a] != ids[b]))
                a, b = a[may], b[may]
                dist = np.sqrt(((f[a] - f[b]) ** 2).sum(1))
                a, b, dist = ids[a][dist < limit], ids[b][dist < limit], dist[dist < limit]
                out.append((np.minimum(a, b), np.maximum(a, b), dist))
        return pa.table([np.concatenate(c) for c in zip(*out, strict=True)], names=["a", "b", "dist"])

    return met.groupBy("x", "y").applyInArrow(near, "a long, b long, dist double").select("a", "b", F.round("dist", 6).alias("dist"))
