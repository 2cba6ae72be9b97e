"""Queries of the methods: tokens, windows, bank, centroids, cluster attention, answers."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.functions.text import paragraphs, words
from longweave.functions.vectors import doubles, dot
from longweave.operators import clusters as C
from longweave.operators import tokens as T
from longweave.operators import windows as W
from longweave.operators.bank import newest
from longweave.operators.fused import DIGEST, digest, per_sequence, states_of
from longweave.operators.refresh import Refresh, Snapshot, fit_stack, refresh_loops, snapshot_table
from longweave.plans import sqltext as S
from longweave.plans.registry import query
from longweave.plans.stack import LayerPlan
from longweave.session import load, persist_cut

D, SEED, WIN, STRIDE, BLOCK = 8, 7, 16, 12, 32
SCALE = 1 / math.sqrt(D)
VSCALE = 0.125  # 1 / sqrt(64)


def docs_packed(spark, sf):
    return T.packed(load(spark, sf, "documents"), "doc_id", "text")


def doc_tokens(spark, sf):
    return T.tokenize(load(spark, sf, "documents"), "doc_id", "text")


def vec_states(spark, sf):
    e = load(spark, sf, "embeddings")
    return e.select(F.lit(0).cast("long").alias("seq_id"), F.col("vec_id").alias("hpos"), F.col("vec_id"), doubles("embedding").alias("vec"))


def vec_chain(spark, sf):
    return C.chain(C.label_means(load(spark, sf, "embeddings")))


def vec_ranked(spark, sf):
    """One sequence of all vectors: ranks come from counts, so no task holds it."""
    return C.cluster_rank_counting(C.nearest(vec_states(spark, sf), vec_chain(spark, sf)), span=4096)


@query("tok_word_counts", f"with {S.TOK} select seq_id, len(t)::int as n_tokens, len(list_distinct(t))::int as n_types from tl")
def tok_word_counts(spark, sf):
    return docs_packed(spark, sf).select("seq_id", F.size("toks").alias("n_tokens"), F.size(F.array_distinct("toks")).alias("n_types"))


@query("tok_char_hist", """select lang, ch, n from (select lang, ch, count(*) as n, row_number() over (partition by lang order by count(*) desc, ch) as r
  from (select lang, unnest(regexp_extract_all(text, '(?s).')) as ch from documents) group by lang, ch) where r <= 20""")  # fmt: skip
def tok_char_hist(spark, sf):
    d = load(spark, sf, "documents")
    n = d.select("lang", F.explode(F.regexp_extract_all("text", F.lit("(?s)."), F.lit(0))).alias("ch")).groupBy("lang", "ch").agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "ch"))).filter("r <= 20").drop("r")


PARAS = r"""pg as (select page_id, regexp_extract_all(regexp_replace(coalesce(html, ''), '(?is)<!--.*?-->|<script.*?</script>|<style.*?</style>', ' ', 'g'), '(?is)<p(?:\s[^>]*)?>(.*?)</p>', 1) as ps from pages),
pa as (select page_id, (i - 1)::int as para_id, trim(regexp_replace(replace(replace(replace(replace(regexp_replace(ps[i], '(?s)<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&'), '\s+', ' ', 'g')) as text
  from (select page_id, ps, unnest(range(1, len(ps) + 1)) as i from pg))"""


def page_paras(spark, sf):
    p = load(spark, sf, "pages").select(F.col("page_id").alias("seq_id"), F.posexplode(paragraphs("html")).alias("para_id", "text"))
    return p


@query("ctx_assemble", rf"""with {PARAS} select page_id as seq_id, count(*) as n_sentinels, (count(*) + sum(n))::bigint as ctx_len, least(count(*) + sum(n), 5000)::bigint as train_len
  from (select page_id, len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) as n from pa) group by page_id""")
def ctx_assemble(spark, sf):
    ctx = T.assemble_context(page_paras(spark, sf))
    size = F.size("toks").cast("long")
    return ctx.select("seq_id", F.size(F.filter("toks", lambda t: t == "<s>")).cast("long").alias("n_sentinels"), size.alias("ctx_len"), F.least(size, F.lit(5000)).cast("long").alias("train_len"))


@query("hash_states_sum", f"with {S.STATES} select (j - 1)::int as j, sum(v)::bigint as s, sum(v * v)::bigint as s2 from (select unnest(vec) as v, generate_subscripts(vec, 1) as j from voc) group by 1")
def hash_states_sum(spark, sf):
    v = T.vocabulary(doc_tokens(spark, sf), D, SEED).select(F.posexplode("vec").alias("j", "v"))
    return v.groupBy("j").agg(F.sum("v").cast("long").alias("s"), F.sum(F.col("v") * F.col("v")).cast("long").alias("s2"))


def _membership(name, win, stride, segment=None):
    cut = "" if segment is None else f", unnest(range((len(t) + {segment - 1}) // {segment})) as seg"
    x = "len(t)" if segment is None else f"least({segment}, len(t) - seg * {segment})"
    seg = "" if segment is None else "seg::int as seg, "
    sql = f"""with {S.TOK}, l as (select seq_id{cut}, t from tl where len(t) > 0), m as (select *, {x} as x from l)
      select seq_id, {seg}k::int as win, (k * {stride})::int as lo, least(x, k * {stride} + {win})::int as hi from (select *, unnest(range((x + {stride - 1}) // {stride})) as k from m)"""

    @query(name, sql)
    def members(spark, sf):
        x = docs_packed(spark, sf).select("seq_id", F.size("toks").alias("x"))
        if segment is None:
            return W.bounds(x, W.WindowSpec(win, stride))
        seg = x.filter("x > 0").withColumn("seg", F.explode(F.sequence(F.lit(0), F.ceil(F.col("x") / segment).cast("int") - 1)))
        seg = seg.select(F.struct("seq_id", "seg").alias("key"), F.least(F.lit(segment), F.col("x") - F.col("seg") * segment).alias("x"))
        return W.bounds(seg, W.WindowSpec(win, stride), key="key").select("key.seq_id", "key.seg", "win", "lo", "hi")


_membership("win_membership", 256, 224)
_membership("win_membership_lm", 256, 128, 3072)


#: Reference form of gold_pairs: passages of fewer than five words name no document.
GOLD = r"documents d join (select * from benchmark where len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) >= 5) b on contains(d.text, b.text)"


def gold_pairs(spark, sf):
    """(doc_id, text, item_id, passage) of documents that hold a passage of five or more words.

    Words 2 to 4 of a passage stand whole in such a document: an equality join on them finds all pairs, contains() decides.
    """
    d, b = load(spark, sf, "documents").select("doc_id", "text"), load(spark, sf, "benchmark").select("item_id", F.col("text").alias("passage"))
    three = lambda t, i: F.xxhash64(F.get(t, i), F.get(t, i + 1), F.get(t, i + 2))
    seeds = b.withColumn("p", words("passage")).filter(F.size("p") >= 5).select("item_id", "passage", three(F.col("p"), F.lit(1)).alias("h"))
    t = d.select("doc_id", words("text").alias("t")).filter(F.size("t") > 2)
    own = t.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("t") - 3), lambda i: three(F.col("t"), i)))).alias("h"))
    pairs = own.join(seeds.select("item_id", "h"), "h").select("doc_id", "item_id").distinct()
    return pairs.join(b, "item_id").join(d, "doc_id").filter(F.contains("text", "passage")).select("doc_id", "text", "item_id", "passage")


@query("win_question_prefix", rf"""with {S.TOK}, g as (select d.doc_id, b.item_id, regexp_split_to_array(trim(lower(b.text)), '\s+') as p from """ + GOLD + rf"""),
  q as (select doc_id, item_id, p[1:len(p) - 3] as q from g),
  w as (select q.item_id, tok.seq_id, k::int as win, (tok.pos - k * 224 + len(q.q))::int as "row", 'c' as kind, tok.tok from (select *, unnest(range(greatest(0, ceil((pos - 255) / 224.0))::bigint, pos // 224 + 1)) as k from tok) tok join q on q.doc_id = tok.seq_id)
  select * from w union all select item_id, seq_id, win, (i - 1)::int, 'q', q[i] from (select w.item_id, w.seq_id, w.win, q.q, unnest(range(1, len(q.q) + 1)) as i from (select distinct item_id, seq_id, win from w) w join q on q.item_id = w.item_id and q.doc_id = w.seq_id)""")
def win_question_prefix(spark, sf):
    g = gold_pairs(spark, sf).select("item_id", F.col("doc_id").alias("seq_id"), words("passage").alias("p"), words("text").alias("t"))
    g = g.withColumn("q", F.slice("p", 1, F.size("p") - 3))
    ctx = g.select("item_id", "seq_id", F.size("q").alias("n"), F.posexplode("t").alias("pos", "tok"))
    w = W.slice_windows(ctx, W.WindowSpec(256, 224)).withColumn("row", (F.col("row") + F.col("n")).cast("int"))
    front = g.select("item_id", "seq_id", "q", F.explode(F.sequence(F.lit(0), F.ceil(F.size("t") / 224).cast("int") - 1)).alias("win"))
    front = front.select("item_id", "seq_id", "win", F.posexplode("q").alias("row", "tok")).withColumn("kind", F.lit("q"))
    return w.select("item_id", "seq_id", "win", "row", F.lit("c").alias("kind"), "tok").unionByName(front)


@query("ctx_truncate", f"with {S.TOK} select seq_id, least(len(t), 5000)::bigint as train_len, least(len(t), 10000)::bigint as infer_len from tl where len(t) > 0")
def ctx_truncate(spark, sf):
    """Tokens left under the caps of training and inference."""
    t = doc_tokens(spark, sf)
    own = T.truncate(t, "infer").groupBy("seq_id").agg(F.count("*").alias("infer_len"))
    return own.join(T.truncate(t, "train").groupBy("seq_id").agg(F.count("*").alias("train_len")), "seq_id")


CODED = ", ".join(f"vec[{j + 1}] + {'sin' if j % 2 == 0 else 'cos'}(r / {10000 ** (2 * (j // 2) / 8)!r}) as o{j + 1}" for j in range(4))


@query("win_position_codes", f"""with {S.STATES}, w as (select seq_id, st.pos - k * 224 as r, vec from (select *, unnest(range(greatest(0, ceil((pos - 255) / 224.0))::bigint, pos // 224 + 1)) as k from st) st),
  o as (select seq_id, {CODED} from w) {S.digest('o')}""")
def win_position_codes(spark, sf):
    """States of all windows with the code of their row in the window added: the same code in each window."""

    def run(seq, toks):
        if not toks:
            return []
        x, codes = states_of(toks, D, SEED), K.position_codes(256, D)
        return digest(seq, np.concatenate([h + codes[: len(h)] for h in K.slice_windows(x, np.empty((0, D)), 256, 224)]))

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


WINROWS = f"(select *, unnest(range(greatest(0, ceil((pos - {WIN - 1}) / {STRIDE}.0))::bigint, pos // {STRIDE} + 1)) as win from st)"
ENCODED = f"with {S.STATES}, w as (select * from {WINROWS}), en as {S.attention('w', 'seq_id, win', 'seq_id, win, pos', SCALE)}"


def encoded_windows(toks):
    x = states_of(toks, D, SEED)
    return x, [K.attention(h, scale=SCALE) for h in K.slice_windows(x, np.empty((0, D)), WIN, STRIDE)]


@query("win_encode_attn", f"{ENCODED} {S.digest('en')}")
def win_encode_attn(spark, sf):
    def run(seq, toks):
        return digest(seq, np.concatenate(encoded_windows(toks)[1])) if toks else []

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


@query("win_encode_padded", f"{ENCODED} {S.digest('en')}")
def win_encode_padded(spark, sf):
    """Short last windows filled up to full length, the filling masked: the rows that count stay what they were."""

    def run(seq, toks):
        if not toks:
            return []
        x, out = states_of(toks, D, SEED), []
        for lo, hi in K.window_bounds(len(x), WIN, STRIDE):
            h = np.concatenate([x[lo:hi], np.full((WIN - (hi - lo), D), 9.0)])
            real = np.broadcast_to(np.arange(WIN) < hi - lo, (WIN, WIN))
            out.append(K.attention(h, scale=SCALE, mask=real)[: hi - lo])
        return digest(seq, np.concatenate(out))

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


def merged_windows(toks):
    x, en = encoded_windows(toks)
    return K.merge_overlaps(en, 0, len(x), WIN, STRIDE)


@query("win_merge_mean", f"{ENCODED}, m as (select seq_id, pos, {', '.join(f'avg(o{j}) as o{j}' for j in range(1, 5))} from en group by 1, 2) {S.digest('m')}")
def win_merge_mean(spark, sf):
    def run(seq, toks):
        return digest(seq, K.dedup_concat(merged_windows(toks), 0, STRIDE)) if toks else []

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


@query("win_dedup", f"with {S.TOK} select seq_id, (len(t) + 20 * ((len(t) + 223) // 224))::bigint as n, (20 * ((len(t) + 223) // 224))::bigint as question_rows from tl where len(t) > 0")
def win_dedup(spark, sf):
    """Rows of the de-duplicated list with a question of 20 rows, counted, not computed."""
    spec = W.WindowSpec(256, 224, 20)
    w = W.slice_windows(doc_tokens(spark, sf), spec)
    kept = W.dedup_concat(w, spec).groupBy("seq_id").agg(F.count("*").alias("c"), (F.max("win") + 1).alias("k"))
    return kept.select("seq_id", (F.col("c") + 20 * F.col("k")).cast("long").alias("n"), (20 * F.col("k")).cast("long").alias("question_rows"))


@query("win_rewindow", f"""{ENCODED}, m as (select seq_id, pos, {', '.join(f'avg(o{j}) as o{j}' for j in range(1, 5))} from en group by 1, 2),
  r as (select m.* from (select *, unnest(range(greatest(0, ceil((pos - {WIN - 1}) / {STRIDE}.0))::bigint, pos // {STRIDE} + 1)) as win from m) m) {S.digest('r')}""")
def win_rewindow(spark, sf):
    def run(seq, toks):
        if not toks:
            return []
        m = merged_windows(toks)
        again = K.rewindow(K.dedup_concat(m, 0, STRIDE), 0, len(toks), WIN, STRIDE)
        assert all(np.array_equal(a, b) for a, b in zip(m, again, strict=True))
        return digest(seq, np.concatenate(again))

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


REFITS_HEAD = f"with {S.window_states(WIN, STRIDE, SCALE)}"


@query("bank_last_n", "select vec_id, round(embedding[1]::double, 6) as c0 from embeddings order by vec_id desc limit 100")
def bank_last_n(spark, sf):
    return newest(load(spark, sf, "embeddings"), 100, "vec_id").select("vec_id", F.round(F.col("embedding")[0].cast("double"), 6).alias("c0"))


@query("bank_after_batches", """with b as (select ((vec_id * 8) // (mx + 1) + 1)::int as iter, vec_id from embeddings cross join (select max(vec_id) as mx from embeddings)),
  h as (select i.iter, b.vec_id, row_number() over (partition by i.iter order by b.vec_id desc) as r from (values (2), (4), (6), (8)) i(iter) join b on b.iter <= i.iter)
  select iter::int as iter, count(*) as held, min(vec_id) as oldest, max(vec_id) as newest from h where r <= 150 group by 1""")
def bank_after_batches(spark, sf):
    """A bank of 150 states that an eighth of the vectors joins at a time: what it holds after each second push."""
    from longweave.operators.bank import MemoryBank
    from longweave.sources.tables import scratch

    e = load(spark, sf, "embeddings").select(F.col("vec_id").alias("arrival"))
    last, out = e.agg(F.max("arrival")).first()[0], []
    bank = MemoryBank(spark, scratch(spark, "bank"), 150)
    for i in range(1, 9) if last is not None else ():
        bank.push(e.filter(F.col("arrival").between(*(-(-(k * (last + 1)) // 8) - j for j, k in enumerate((i - 1, i))))), i)
        bank.evict()
        if i % 2 == 0:
            out.append((i, *bank.read().agg(F.count("*"), F.min("arrival"), F.max("arrival")).first()))
    return spark.createDataFrame(out, "iter int, held long, oldest long, newest long")


@query("bank_source", f"""{REFITS_HEAD}, wn as (select h.vec from (select *, unnest(range(greatest(0, ceil((pos - {WIN - 1}) / {STRIDE}.0))::bigint, pos // {STRIDE} + 1)) as k from hs) h),
  srcs as (select 'windows' as source, vec from wn union all select 'dedup', vec from hs)
  select source, count(*) as n, {', '.join(f'round(avg(vec[{j}]), 6) + 0.0 as m{j}' for j in range(1, 5))} from srcs group by 1""")
def bank_source(spark, sf):
    """What a bank sees if merged windows are pushed with their overlaps, or the de-duplicated list: its size and mean."""

    def run(seq, toks):
        if not toks:
            return []
        x = window_layer(toks)
        kinds = {"dedup": x, "windows": np.concatenate([x[a:z] for a, z in K.window_bounds(len(x), WIN, STRIDE)])}
        return [{"source": k, "n": len(h)} | {f"t{j + 1}": float(h[:, j].sum()) for j in range(4)} for k, h in kinds.items()]

    each = per_sequence(docs_packed(spark, sf), run, "source string, n long, t1 double, t2 double, t3 double, t4 double").groupBy("source")
    return each.agg(F.sum("n").alias("n"), *((F.round(F.sum(f"t{j}") / F.sum("n"), 6) + 0.0).alias(f"m{j}") for j in range(1, 5)))


@query("centroid_random_start", f"with {S.CENT}, r as (select cid, list_transform({S.hash_vec(chr(39) + 'centroid' + chr(39) + ' || cid')}, lambda y: y * (1 + 0.0137 * cid)::double) as h from c) select ce.cid::int as cid, (j - 1)::int as j, round(h[j], 6) + 0.0 as v, round(ce.v, 6) + 0.0 as mean from ce join r using (cid) where j <= len(h)")
def centroid_random_start(spark, sf):
    """What labels are made with before the first refresh, for each label of the vectors; beside it the mean of these."""
    start = F.pandas_udf(lambda cid: cid.map(lambda i: start_vector(i, D).tolist()), "array<double>")
    t = C.label_means(load(spark, sf, "embeddings")).withColumn("h", start("cid"))
    t = t.select(F.col("cid").cast("int").alias("cid"), "vec", F.posexplode("h").alias("j", "v"))
    return t.select("cid", "j", (F.round("v", 6) + 0.0).alias("v"), (F.round(F.get("vec", "j"), 6) + 0.0).alias("mean")).filter("mean is not null")


@query("kmeans_one_step", f"""with {S.CENT}, a as (select vec, cid from (select e.vec_id, e.embedding::double[] as vec, c.cid, row_number() over (partition by e.vec_id order by list_distance(e.embedding::double[], c.vec), c.cid) as rn from embeddings e, c) where rn = 1)
  select cid::int as cid, (j - 1)::int as j, count(*) as n, round(avg(v), 6) as v from (select cid, unnest(vec) as v, generate_subscripts(vec, 1) as j from a) group by 1, 2""")
def kmeans_one_step(spark, sf):
    rows = C.label_means(load(spark, sf, "embeddings")).orderBy("cid").collect()
    step = C.kmeans_step(vec_states(spark, sf), np.array([r["vec"] for r in rows]))
    names = F.array(*(F.lit(r["cid"]) for r in rows))
    return step.filter("n > 0").select(names[F.col("cid")].cast("int").alias("cid"), F.posexplode("vec").alias("j", "v"), "n").select("cid", "j", "n", F.round("v", 6).alias("v"))


@query("kmeans_unit_step", f"""with {S.CENT}, u as (select vec_id, list_transform(embedding::double[], lambda y: y / sqrt(list_dot_product(embedding::double[], embedding::double[]))) as vec from embeddings),
  n as (select cid, list_transform(vec, lambda y: y / sqrt(list_dot_product(vec, vec))) as vec from c),
  a as (select vec, cid from (select u.vec_id, u.vec, n.cid, row_number() over (partition by u.vec_id order by list_distance(u.vec, n.vec), n.cid) as rn from u, n) where rn = 1)
  select cid::int as cid, (j - 1)::int as j, count(*) as n, round(avg(v), 6) as v from (select cid, unnest(vec) as v, generate_subscripts(vec, 1) as j from a) group by 1, 2""")
def kmeans_unit_step(spark, sf):
    """One step among unit vectors, where the nearest by distance is the nearest by cosine."""
    rows = C.label_means(load(spark, sf, "embeddings")).orderBy("cid").collect()
    c = np.array([r["vec"] for r in rows])
    unit = vec_states(spark, sf).withColumn("vec", F.transform("vec", lambda x: x / F.sqrt(dot("vec", "vec"))))
    step = C.kmeans_step(unit, c / np.linalg.norm(c, axis=1, keepdims=True))
    names = F.array(*(F.lit(r["cid"]) for r in rows))
    return step.filter("n > 0").select(names[F.col("cid")].cast("int").alias("cid"), F.posexplode("vec").alias("j", "v"), "n").select("cid", "j", "n", F.round("v", 6).alias("v"))


@query("centroid_chain", f"with recursive {S.CENT}, {S.CHAIN} select ord::int as ord, cid::int as cid, round(list_cosine_similarity(vec, lag(vec) over (order by ord)), 6) as to_previous from chain")
def centroid_chain(spark, sf):
    from longweave.functions.vectors import cosine

    c = vec_chain(spark, sf).withColumn("p", F.lag("vec").over(Window.orderBy("ord")))
    return c.select("ord", "cid", F.when(F.col("p").isNotNull(), F.round(cosine("vec", "p"), 6)).alias("to_previous"))


for _metric, _near in (("cosine", S.COSINE), ("dot", "list_dot_product(e.embedding::double[], k.vec)"), ("l2", "-list_distance(e.embedding::double[], k.vec)")):

    @query(f"assign_{_metric}", f"{S.vectors_slice(_near)} select vec_id, cluster::int as cluster from asg")
    def _assign(spark, sf, metric=_metric):
        return C.nearest(vec_states(spark, sf), vec_chain(spark, sf), metric).select("vec_id", "cluster")


@query("assign_fast", f"{S.vectors_slice()} select vec_id, cluster::int as cluster from asg")
def assign_fast(spark, sf):
    """The same labels by one matrix product for each Arrow batch."""
    cent = np.array([r["vec"] for r in vec_chain(spark, sf).orderBy("ord").collect()])  # one row for each centroid
    return C.nearest_fast(vec_states(spark, sf), cent).select("vec_id", "cluster")


@query("cal_rank", f"{S.vectors_slice()} select vec_id, cluster::int as cluster, srank from ranked")
def cal_rank(spark, sf):
    return vec_ranked(spark, sf).select("vec_id", "cluster", "srank")


@query("cal_blocks", f"{S.vectors_slice()} select vec_id, (srank // {BLOCK})::int as block from ranked")
def cal_blocks(spark, sf):
    """By the counting rank, which needs no task for a whole sequence."""
    ranked = C.cluster_rank_counting(C.nearest(vec_states(spark, sf), vec_chain(spark, sf)), span=128)
    return C.chunk(ranked, BLOCK).select("vec_id", "block")


@query("cal_restore", f"{S.vectors_slice()}, bk as (select vec_id, vec, srank, srank // {BLOCK} as block from ranked), o as {S.attention('bk', 'block', 'vec_id', VSCALE)} select o.vec_id, ranked.srank, round(o.o1, 6) + 0.0 as o1 from o join ranked using (vec_id)")
def cal_restore(spark, sf):
    """States leave their blocks in sorted order (srank); the permutation, kept apart, says whose they are."""
    ranked = persist_cut(vec_ranked(spark, sf))
    perm = ranked.select("srank", "vec_id")
    sorted_rows = C.attend(C.chunk(ranked, BLOCK).withColumn("hpos", F.col("srank")), ["seq_id", "block"], VSCALE)
    return sorted_rows.select(F.col("hpos").alias("srank"), (F.round(F.col("out")[0], 6) + 0.0).alias("o1")).join(perm, "srank").select("vec_id", "srank", "o1")


@query("cal_strict_blocks", f"{S.vectors_slice()} select vec_id, cluster::int as cluster, ((row_number() over (partition by cluster order by vec_id) - 1) // {BLOCK})::int as sub from asg")
def cal_strict_blocks(spark, sf):
    b = C.chunk(vec_ranked(spark, sf), BLOCK, "strict")
    return b.select("vec_id", "cluster", (F.col("block") % 1_000_000).cast("int").alias("sub"))


@query("cal_padded_cost", f"""{S.vectors_slice()}, s as (select cluster, count(*) as n from asg group by 1)
  select count(*) as clusters, max(n) as largest, (count(*) * max(n) * max(n))::bigint as padded_pairs, sum(n * n)::bigint as strict_pairs,
  ((sum(n) // {BLOCK}) * {BLOCK * BLOCK} + (sum(n) % {BLOCK}) * (sum(n) % {BLOCK}))::bigint as uniform_pairs, round(count(*) * max(n) * max(n) / sum(n * n), 6) as waste from s""")
def cal_padded_cost(spark, sf):
    n = C.nearest(vec_states(spark, sf), vec_chain(spark, sf)).groupBy("cluster").agg(F.count("*").alias("n"))
    a = n.agg(F.count("*").alias("clusters"), F.max("n").alias("largest"), F.sum(F.col("n") * F.col("n")).alias("strict_pairs"), F.sum("n").alias("t"))
    padded, rest = F.col("clusters") * F.col("largest") * F.col("largest"), F.col("t") % BLOCK
    return a.select("clusters", "largest", padded.alias("padded_pairs"), "strict_pairs", (F.floor(F.col("t") / BLOCK) * BLOCK * BLOCK + rest * rest).alias("uniform_pairs"), F.round(padded / F.col("strict_pairs"), 6).alias("waste"))


@query("cal_attn_vectors", f"{S.vectors_slice()}, b as (select vec_id, vec, srank // {BLOCK} as block from ranked), o as {S.attention('b', 'block', 'vec_id', VSCALE)} select vec_id, {', '.join(f'round(o{j}, 6) + 0.0 as o{j}' for j in range(1, 5))} from o")
def cal_attn_vectors(spark, sf):
    out = C.attend(C.chunk(vec_ranked(spark, sf), BLOCK), ["seq_id", "block"], VSCALE)
    return out.select(F.col("hpos").alias("vec_id"), *((F.round(F.col("out")[j], 6) + 0.0).alias(f"o{j + 1}") for j in range(4)))


def window_layer(toks, d=D, causal=False):
    """States of a document after one window layer, overlaps merged: what lies below the cluster-attention layer."""
    x = states_of(toks, d, SEED)
    none = np.empty((-(-len(x) // STRIDE), 0, d))
    past = (lambda h: K.attention(h, scale=1 / math.sqrt(d), mask=np.tril(np.ones((h.shape[1],) * 2, bool)))) if causal else (lambda h: K.attention(h, scale=1 / math.sqrt(d)))
    return K.encode_merged(x, none, WIN, STRIDE, past)[0]


REFRESH = Refresh(cap=100_000, iterations=4, every=2, steps=4)
_fitted: dict[tuple, list[Snapshot]] = {}


def start_vector(i, d=D):
    return K.token_vector(f"centroid{i}", d, SEED) * (1 + 0.0137 * i)


def random_start(p=16, d=D):
    """Random vectors, no two of them equally far from a state of whole numbers."""
    return np.array([start_vector(i, d) for i in range(p)])


def text_snapshots(spark, sf, p=16, how=REFRESH, d=D, causal=False) -> list[Snapshot]:
    """The refreshes of one pass over the documents, once per session and table."""
    return several_snapshots(spark, sf, (p,), how, d, causal)[0]


def several_snapshots(spark, sf, ps, how=REFRESH, d=D, causal=False) -> list[list[Snapshot]]:
    """text_snapshots for each of ps; those not there yet share one pass and its bank."""
    key = lambda p: (spark.sparkContext.applicationId, sf, p, how, d, causal)
    inits = {p: random_start(p, d) for p in ps if key(p) not in _fitted}
    if inits:
        got = refresh_loops(docs_packed(spark, sf), lambda toks: window_layer(toks, d, causal), list(inits.values()), how)
        for (p, init), snapshots in zip(inits.items(), got, strict=True):
            _fitted[key(p)] = snapshots or [Snapshot(0, init, 0.0)]
    return [_fitted[key(p)] for p in ps]


def text_centroids(spark, sf, p=16, **k):
    """The newest snapshot in chain order: what labels are made with."""
    return text_snapshots(spark, sf, p, **k)[-1].ordered


FITTED = f"{S.window_states(WIN, STRIDE, SCALE)}, {S.refreshed(16, REFRESH.cap, REFRESH.iterations, REFRESH.every, REFRESH.steps)}, {S.CHAIN}, {S.LABEL_STATES}"
LABELLED = f"with recursive {FITTED}, lab as (select seq_id, pos, vec, cluster, (row_number() over (partition by seq_id order by cluster, pos) - 1) // {BLOCK} as block from lab0)"


@query("cal_text_states", f"{LABELLED}, o as {S.attention('lab', 'seq_id, block', 'seq_id, pos', SCALE)} {S.digest('o')}")
def cal_text_states(spark, sf):
    """Window layer, labels by the fitted centroids, sort, blocks, attention, order restored: no exchange."""
    cent = text_centroids(spark, sf)

    def run(seq, toks):
        if not toks:
            return []
        x = window_layer(toks)
        return digest(seq, K.cluster_attention(x, K.assign(x, cent), BLOCK, lambda h: K.attention(h, scale=SCALE)))

    return per_sequence(docs_packed(spark, sf), run, DIGEST)


def _text_layout(name, sql, layout, ordered=True):
    @query(name, sql)
    def run(spark, sf):
        last = text_snapshots(spark, sf)[-1]
        cent = last.ordered if ordered else last.centroids

        def one(seq, toks):
            if not toks:
                return []
            x = window_layer(toks)
            return digest(seq, K.cluster_attention(x, K.assign(x, cent), BLOCK, K_ATT, layout))

        return per_sequence(docs_packed(spark, sf), one, DIGEST)


def K_ATT(h, mask=None):
    return K.attention(h, scale=SCALE, mask=mask)


UNCHAINED = f"with recursive {S.window_states(WIN, STRIDE, SCALE)}, {S.refreshed(16, REFRESH.cap, REFRESH.iterations, REFRESH.every, REFRESH.steps)}, chain as (select cid as ord, cid, vec from c), {S.LABEL_STATES}, lab as (select seq_id, pos, vec, cluster, (row_number() over (partition by seq_id order by cluster, pos) - 1) // {BLOCK} as block from lab0)"
# within blocks only rows of the same cluster read each other; whole clusters as (padded) blocks; no greedy walk
_text_layout("cal_masked", f"{LABELLED}, o as {S.attention('lab', 'seq_id, block, cluster', 'seq_id, pos', SCALE)} {S.digest('o')}", "masked")
_text_layout("cal_padded", f"{LABELLED}, o as {S.attention('lab', 'seq_id, cluster', 'seq_id, pos', SCALE)} {S.digest('o')}", "padded")
_text_layout("cal_unordered", f"{UNCHAINED}, o as {S.attention('lab', 'seq_id, block', 'seq_id, pos', SCALE)} {S.digest('o')}", "uniform", ordered=False)
REFITS = f"with recursive {S.window_states(WIN, STRIDE, SCALE)}, {S.refreshed(16, REFRESH.cap, REFRESH.iterations, REFRESH.every, REFRESH.steps)}"


@query("refresh_snapshots", f"{REFITS} select epoch::int as epoch, cid::int as cid, (j - 1)::int as j, round(v, 6) + 0.0 as v from (select epoch, cid, unnest(vec) as v, generate_subscripts(vec, 1) as j from (select 1 as epoch, cid, vec from r1 union all select 2, cid, vec from r2))")
def refresh_snapshots(spark, sf):
    """The centroids after each refresh of one pass over the documents: push, evict, K-Means over the bank."""
    rows = [(s.epoch, k, v.tolist()) for s in text_snapshots(spark, sf) for k, v in enumerate(s.centroids)]
    t = spark.createDataFrame(rows, "epoch int, cid int, vec array<double>")
    return t.select("epoch", "cid", F.posexplode("vec").alias("j", "v")).withColumn("v", F.round("v", 6) + 0.0)


@query("layer_rule_grid", """with g as (select a::int as a, b::int as b, base::int as base, coalesce((select list(k::int order by k) from range(1, 25) r(k) where (k - 1 + base) % a = 0 and k - 1 + base >= b), []::int[]) as depths
  from range(3, 7) x(a), (select unnest([8, 12, 16, 20]) as b) y, range(2) z(base)), w as (select sum((n_chars + 223) // 224)::bigint as n from documents)
  select a, b, base, depths::varchar as depths, (len(depths) * n)::bigint as passes from g, w""")
def layer_rule_grid(spark, sf):
    """The depths that attend within clusters by each rule, and the windows of 224 characters that pass through these."""
    windows = load(spark, sf, "documents").agg(F.sum(F.floor((F.col("n_chars") + 223) / 224)).alias("n"))  # one row
    grid = spark.range(3, 7).toDF("a").crossJoin(spark.createDataFrame([(b,) for b in (8, 12, 16, 20)], "b int")).crossJoin(spark.range(2).toDF("base")).crossJoin(F.broadcast(windows))
    depths = F.filter(F.sequence(F.lit(1), F.lit(24)), lambda k: ((k - 1 + F.col("base")) % F.col("a") == 0) & (k - 1 + F.col("base") >= F.col("b")))
    shown = F.concat(F.lit("["), F.array_join(depths.cast("array<string>"), ", "), F.lit("]"))
    return grid.select(F.col("a").cast("int").alias("a"), "b", F.col("base").cast("int").alias("base"), shown.alias("depths"), (F.size(depths) * F.col("n")).alias("passes"))


@query("snapshot_asof", f"""with {S.TOK}, its as (select (seq_id * 4) // (mx + 1) + 1 as it from (select seq_id from tl where len(t) > 0) cross join (select max(seq_id) as mx from tl))
  select (it // 2)::int as epoch, count(*) as n, case when it // 2 = 0 then 0 else 16 end::bigint as centroids from its group by it // 2""")
def snapshot_asof(spark, sf):
    """Which snapshot a document meets in the stream: the last one fitted by its iteration (0: random vectors)."""
    kept = snapshot_table(spark, 2, text_snapshots(spark, sf)).groupBy("epoch").agg(F.count("*").alias("centroids"))
    d = docs_packed(spark, sf)
    last = d.agg((F.max("seq_id") + 1).alias("m"))  # one row
    it = F.expr(f"seq_id * {REFRESH.iterations} div m + 1")
    own = d.filter(F.size("toks") > 0).crossJoin(F.broadcast(last)).select(F.floor(it / REFRESH.every).cast("int").alias("epoch")).groupBy("epoch").agg(F.count("*").alias("n"))
    return own.join(kept, "epoch", "left").select("epoch", "n", F.coalesce("centroids", F.lit(0)).cast("long").alias("centroids"))


VALID = "('0x' || substr(md5(seq_id::varchar), 1, 8))::bigint % 100 < 5"


def valid_fold(seq_id="seq_id"):
    return F.conv(F.substring(F.md5(F.col(seq_id).cast("string")), 1, 8), 16, 10).cast("long") % 100 < 5


@query("centroid_select_best", f"""{REFITS}, al as (select 1 as epoch, vec as k from r1 union all select 2, vec from r2),
  near as (select epoch, seq_id, pos, max(list_cosine_similarity(h.vec, al.k)) as s from hs h, al where {VALID} group by 1, 2, 3),
  sc as (select epoch, count(*) as n, avg(s) as score from near group by 1) select 2::int as layer, epoch::int as epoch, n, round(score, 6) as score from sc order by score desc, epoch limit 1""")
def centroid_select_best(spark, sf):
    """Of the snapshots of all refreshes, the one whose centroids lie nearest to the states of the validation documents."""
    snapshots = text_snapshots(spark, sf)

    def run(seq, toks):
        x = window_layer(toks) if toks else np.empty((0, D))
        return [{"epoch": s.epoch, "n": len(x), "total": float(K.similarity(x, s.centroids).max(1).sum())} for s in snapshots] if len(x) else []

    each = per_sequence(docs_packed(spark, sf).filter(valid_fold()), run, "epoch int, n long, total double").groupBy("epoch").agg(F.sum("n").alias("n"), F.sum("total").alias("t"))
    best = each.select(F.lit(2).alias("layer"), "epoch", "n", F.round(F.col("t") / F.col("n"), 6).alias("score"))
    return best.orderBy(F.desc("score"), "epoch").limit(1)


# ---------------------------------------------------------------- answers
POOL = f"""with {S.STATES}, f as (select seq_id, pos // 224 as win, vec from st where pos % 224 = 0) """


@query("qa_pool_first", f"{POOL} select seq_id, (j - 1)::int as j, round(avg(v), 6) + 0.0 as v from (select seq_id, unnest(vec) as v, generate_subscripts(vec, 1) as j from f) group by 1, 2")
def qa_pool_first(spark, sf):
    """Mean of the first state of each window; the filter on the row comes before states are made."""
    t = doc_tokens(spark, sf).filter(F.col("pos") % 224 == 0)
    v = T.embed(t, D, SEED).select("seq_id", F.posexplode("vec").alias("j", "v"))
    return v.groupBy("seq_id", "j").agg((F.round(F.avg("v"), 6) + 0.0).alias("v"))


HEAD = [1.0, -1.0, 2.0, 0.0, 0.5, -0.5, 1.0, -2.0]
QUESTION = K.token_vector("question", D, SEED).tolist()


@query("qa_rank_paras", rf"""with {PARAS}, f as (select page_id, para_id, (list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> ''))[1] as tok from pa),
  s as (select page_id as seq_id, para_id, round(list_dot_product({S.hash_vec('tok')}, {HEAD}::double[]), 6) + 0.0 as score from f where tok is not null)
  select * from (select *, (row_number() over (partition by seq_id order by score desc, para_id))::int as rank from s) where rank <= 3""")
def qa_rank_paras(spark, sf):
    """Candidates by the score of the state at their head, the best three per page."""
    p = page_paras(spark, sf).select("seq_id", "para_id", words("text").alias("t")).filter(F.size("t") > 0)
    s = T.embed(p.select("seq_id", "para_id", F.col("t")[0].alias("tok")), D, SEED)
    s = s.select("seq_id", "para_id", (F.round(dot("vec", F.array(*map(F.lit, HEAD))), 6) + 0.0).alias("score"))
    return s.withColumn("rank", F.row_number().over(Window.partitionBy("seq_id").orderBy(F.desc("score"), "para_id"))).filter("rank <= 3")


SPAN = f"""with {S.STATES}, sc as (select seq_id, pos, list_dot_product(vec, {QUESTION}::double[]) as a, list_dot_product(vec, {HEAD}::double[]) as z from st),
  sp as (select x.seq_id, x.pos as lo, y.pos as hi, x.a + y.z as score from sc x join sc y on x.seq_id = y.seq_id and y.pos between x.pos and x.pos + 7),
  best as (select seq_id, lo, hi, score from (select *, row_number() over (partition by seq_id order by score desc, lo, hi) as rn from sp) where rn = 1)"""


def best_spans(spark, sf):
    """Per sequence the span of at most 8 tokens with the best start + end score: one narrow pass, the best end of each
    start comes from a sliding maximum."""
    q, z = np.array(QUESTION), np.array(HEAD)

    def run(seq, toks):
        if not toks:
            return []
        x = states_of(toks, D, SEED)
        start, end = x @ q, np.concatenate([x @ z, np.full(7, -np.inf)])
        ahead = np.lib.stride_tricks.sliding_window_view(end, 8)
        total = start + ahead.max(1)
        lo = int(total.argmax())  # the first of equals; its end likewise
        return {"seq_id": seq, "lo": lo, "hi": lo + int(ahead[lo].argmax()), "score": float(total[lo])}

    return per_sequence(docs_packed(spark, sf), run, "seq_id long, lo int, hi int, score double")


@query("qa_best_span", f"{SPAN} select seq_id, lo::int as lo, hi::int as hi, round(score, 6) as score from best")
def qa_best_span(spark, sf):
    return best_spans(spark, sf).withColumn("score", F.round("score", 6))


@query("qa_null_threshold", f"{SPAN} select seq_id, case when score > 400 then lo::int end as lo, case when score > 400 then hi::int end as hi from best")
def qa_null_threshold(spark, sf):
    keep = F.col("score") > 400
    return best_spans(spark, sf).select("seq_id", F.when(keep, F.col("lo")).alias("lo"), F.when(keep, F.col("hi")).alias("hi"))


@query("qa_ensemble", f"with m as (select vec_id, unnest([list_dot_product(embedding[1:8]::double[], {S.hash_vec(chr(39) + 'm1' + chr(39))}), list_dot_product(embedding[1:8]::double[], {S.hash_vec(chr(39) + 'm2' + chr(39))}), list_dot_product(embedding[1:8]::double[], {S.hash_vec(chr(39) + 'm3' + chr(39))})]) as s from embeddings) select vec_id, round(avg(s), 6) + 0.0 as score from m group by 1")
def qa_ensemble(spark, sf):
    e = vec_states(spark, sf).select("vec_id", F.slice("vec", 1, 8).alias("v"))
    out = None
    for m in ("m1", "m2", "m3"):
        s = e.select("vec_id", dot("v", F.array(*map(F.lit, K.token_vector(m, D, SEED).tolist()))).alias("s"))
        out = s if out is None else out.unionByName(s)
    return out.groupBy("vec_id").agg((F.round(F.avg("s"), 6) + 0.0).alias("score"))


@query("qa_split", "select case when ('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 100 < 5 then 'valid' else 'train' end as fold, count(*) as n from documents group by 1")
def qa_split(spark, sf):
    bucket = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 100
    return load(spark, sf, "documents").groupBy(F.when(bucket < 5, "valid").otherwise("train").alias("fold")).agg(F.count("*").alias("n"))


def labelled(spark, sf):
    """(seq_id, pos, tok, cluster, block) of all tokens, by whole-sequence kernel."""
    cent = text_centroids(spark, sf)

    def run(seq, toks):
        if not toks:
            return []
        lab = K.assign(window_layer(toks), cent)
        block = np.empty(len(toks), dtype=int)
        for k, rows in enumerate(K.blocks_of(lab, BLOCK)):
            block[rows] = k
        return {"seq_id": seq, "t": [{"pos": i, "tok": toks[i], "cluster": int(lab[i]), "block": int(block[i])} for i in range(len(toks))]}

    return per_sequence(docs_packed(spark, sf), run, "seq_id long, t array<struct<pos:int,tok:string,cluster:int,block:int>>").select("seq_id", F.explode("t").alias("x")).select("seq_id", "x.*")


WORDS_OF = "wc as (select lab.cluster, tok.tok, count(*) as n from tok join lab using (seq_id, pos) group by 1, 2), top as (select *, row_number() over (partition by cluster order by n desc, tok) as r from wc)"


def frequent_words(labels, top=10):
    n = labels.groupBy("cluster", "tok").agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(Window.partitionBy("cluster").orderBy(F.desc("n"), "tok"))).filter(F.col("r") <= top)


@query("cluster_words", f"{LABELLED}, {WORDS_OF} select cluster::int as cluster, sum(n)::bigint as n, string_agg(tok, ' ' order by r) as members from top where r <= 10 group by 1")
def cluster_words(spark, sf):
    """The ten most frequent words of each cluster of states."""
    w = frequent_words(labelled(spark, sf))
    return w.groupBy("cluster").agg(F.sum("n").alias("n"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "tok"))), lambda x: x["tok"]), " ").alias("members"))


@query("cluster_positions", f"{LABELLED} select seq_id, cluster::int as cluster, count(*) as n, min(pos)::int as lo, max(pos)::int as hi, (max(pos) - min(pos))::int as reach, round(avg(pos), 6) as mean_pos from lab group by 1, 2")
def cluster_positions(spark, sf):
    """Where the states of a cluster stand in each document, and how far apart."""
    return labelled(spark, sf).groupBy("seq_id", "cluster").agg(F.count("*").alias("n"), F.min("pos").alias("lo"), F.max("pos").alias("hi"), (F.max("pos") - F.min("pos")).alias("reach"), F.round(F.avg("pos"), 6).alias("mean_pos"))


@query("cluster_runs", f"{LABELLED}, i as (select seq_id, cluster, pos - row_number() over (partition by seq_id, cluster order by pos) as g from lab), r as (select seq_id, cluster, g, count(*) as n from i group by 1, 2, 3) select cluster::int as cluster, count(*) as runs, max(n) as longest from r group by 1")
def cluster_runs(spark, sf):
    """Runs of neighbouring positions in one cluster."""
    g = F.col("pos") - F.row_number().over(Window.partitionBy("seq_id", "cluster").orderBy("pos"))
    r = labelled(spark, sf).withColumn("g", g).groupBy("seq_id", "cluster", "g").agg(F.count("*").alias("n"))
    return r.groupBy("cluster").agg(F.count("*").alias("runs"), F.max("n").alias("longest"))


_stacks: dict[tuple, LayerPlan] = {}


def fitted_stack(spark, sf, plan: LayerPlan, how=REFRESH) -> LayerPlan:
    """plan with centroids fitted on the documents, once per session."""
    key = (spark.sparkContext.applicationId, sf, repr(plan), how)
    if key not in _stacks:
        _stacks[key] = fit_stack(docs_packed(spark, sf), plan, lambda toks: states_of(toks, plan.d, plan.seed), how)
    return _stacks[key]


@query("cal_numpy_stack")
def cal_numpy_stack(spark, sf):
    """The whole stack per document: window layers, cluster attention at its depths, seeded blocks."""
    plan = fitted_stack(spark, sf, LayerPlan.explicit([2, 4], n_layers=5))
    return per_sequence(docs_packed(spark, sf), lambda seq, toks: plan.digest(seq, toks), DIGEST)
