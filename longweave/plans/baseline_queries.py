"""Queries of the baselines, on the same states and geometry as the cluster-attention layer."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.functions.text import words
from longweave.functions.vectors import dot
from longweave.operators import tokens as T
from longweave.operators.fused import DIGEST, digest, per_sequence, states_of
from longweave.plans import sqltext as S
from longweave.plans.method_queries import BLOCK, D, ENCODED, GOLD, HEAD, PARAS, QUESTION, SCALE, SEED, STRIDE, WIN, WINROWS, docs_packed, fitted_stack, gold_pairs, merged_windows, page_paras
from longweave.plans.registry import query
from longweave.plans.stack import LayerPlan
from longweave.session import load

ATT = lambda h: K.attention(h, scale=SCALE)
DIRECTIONS = np.array([K.token_vector(f"direction{i}", D, SEED) for i in range(16)])
DIR_SQL = f"dirs as (select i as b, {S.hash_vec(chr(39) + 'direction' + chr(39) + ' || i')} as dv from range(16) r(i))"


def _fused(name: str, sql: str | None, fn):
    """A query of fn(states of a document) by whole-sequence kernel."""

    @query(name, sql)
    def run(spark, sf):
        return per_sequence(docs_packed(spark, sf), lambda seq, toks: digest(seq, fn(states_of(toks, D, SEED))) if toks else [], DIGEST)


@query("base_local", f"{ENCODED}, m as (select seq_id, pos, {', '.join(f'avg(o{j}) as o{j}' for j in range(1, 5))} from en group by 1, 2) {S.digest('m')}")
def base_local(spark, sf):
    return per_sequence(docs_packed(spark, sf), lambda seq, toks: digest(seq, K.dedup_concat(merged_windows(toks), 0, STRIDE)) if toks else [], DIGEST)


def _windows(x):
    return K.slice_windows(x, np.empty((0, D)), WIN, STRIDE)


SAME = f'with {S.STATES}, w as (select seq_id, win, pos - win * {STRIDE} as "row", vec from {WINROWS})'
_fused("base_same_position", f"""{SAME}, o as {S.attention('w', 'seq_id, "row"', 'seq_id, "row", win', SCALE)} {S.digest('o')}""", lambda x: np.concatenate(K.same_position(_windows(x), None, ATT)))
_fused("base_same_position_subset", f"""{SAME}, s as (select * from w where "row" < 4), a as {S.attention('s', 'seq_id, "row"', 'seq_id, "row", win', SCALE)},
  o as (select seq_id, o1, o2, o3, o4 from a union all select seq_id, vec[1], vec[2], vec[3], vec[4] from w where "row" >= 4) {S.digest('o')}""", lambda x: np.concatenate(K.same_position(_windows(x), [0, 1, 2, 3], ATT)))  # fmt: skip


def _hash_sql(signed: bool) -> str:
    more = " union all select b + 16, list_transform(dv, lambda y: -y) from dirs" if signed else ""
    return f"""with {S.STATES}, {DIR_SQL}, alld as (select b, dv from dirs{more}),
      nb as (select vec, arg_min(b, (-near, b)) as bucket from (select v.vec, d.b, list_dot_product(v.vec, d.dv) as near from (select distinct vec from voc) v, alld d) group by vec),
      b as (select seq_id, pos, vec, (row_number() over (partition by seq_id order by bucket, pos) - 1) // {BLOCK} as block from st join nb using (vec)),
      o as {S.attention('b', 'seq_id, block', 'seq_id, pos', SCALE)} {S.digest('o')}"""


_fused("base_random_hash", _hash_sql(False), lambda x: K.random_hash(x, DIRECTIONS, BLOCK, encode=ATT))
_fused("base_random_hash_signed", _hash_sql(True), lambda x: K.random_hash(x, DIRECTIONS, BLOCK, signed=True, encode=ATT))
_fused("base_sorted_buckets", f"""with {S.STATES}, {DIR_SQL}, k as (select st.*, list_dot_product(vec, (select dv from dirs where b = 0)) as key from st),
  b as (select seq_id, pos, vec, (row_number() over (partition by seq_id order by key, pos) - 1) // {BLOCK} as block from k), o as {S.attention('b', 'seq_id, block', 'seq_id, pos', SCALE)} {S.digest('o')}""", lambda x: K.sorted_buckets(x, DIRECTIONS[0], BLOCK))  # fmt: skip
_fused("base_carry_memory", f"""with {S.STATES}, w as (select seq_id, win, pos, vec from {WINROWS}), k as (select seq_id, win, vec from w union all select seq_id, win + 1, vec from w),
  e as (select a.seq_id, a.win, a.pos, exp(list_dot_product(a.vec, k.vec) * {SCALE!r}) as e, k.vec[1] as v1, k.vec[2] as v2, k.vec[3] as v3, k.vec[4] as v4 from w a join k using (seq_id, win)),
  o as (select seq_id, win, pos, {', '.join(f'sum(e * v{j}) / sum(e) as o{j}' for j in range(1, 5))} from e group by 1, 2, 3) {S.digest('o')}""", lambda x: np.concatenate(K.carry_memory(_windows(x))))
_fused("base_random_hash_rounds", f"""with {S.STATES}, {DIR_SQL}, nb as (select vec, r, arg_min(b, (-near, b)) as bucket from (select v.vec, d.b, d.b // 4 as r, list_dot_product(v.vec, d.dv) as near from (select distinct vec from voc) v, dirs d) group by vec, r),
  b as (select seq_id, pos, r, vec, (row_number() over (partition by seq_id, r order by bucket, pos) - 1) // {BLOCK} as block from st join nb using (vec)),
  each as {S.attention('b', 'seq_id, r, block', 'seq_id, r, pos', SCALE)}, o as (select seq_id, pos, {', '.join(f'avg(o{j}) as o{j}' for j in range(1, 5))} from each group by 1, 2) {S.digest('o')}""", lambda x: K.random_hash(x, DIRECTIONS, BLOCK, rounds=4, encode=ATT))

TURNS = r"""tl as (select conv_id * 1000 + turn as seq_id, list_filter(regexp_split_to_array(trim(lower(coalesce(text, ''))), '\s+'), lambda y: y <> '') as t from conversations),
tok as (select seq_id, unnest(t) as tok, (generate_subscripts(t, 1) - 1)::int as pos from tl)""" + f", voc as (select tok, {S.hash_vec('tok')} as vec from (select distinct tok from tok)), st as (select tok.seq_id, tok.pos, voc.vec from tok join voc using (tok))"


@query("base_dense_small", f"with {TURNS}, o as {S.attention('st', 'seq_id', 'seq_id, pos', SCALE)} {S.digest('o')}")
def base_dense_small(spark, sf):
    """Every token of a turn reads every other; sequences over 10,000 tokens are refused, not cut."""
    c = load(spark, sf, "conversations").withColumn("k", F.col("conv_id") * 1000 + F.col("turn"))

    def run(seq, toks):
        if len(toks) > 10_000:
            raise ValueError(f"sequence {seq} is too long for dense attention")
        return digest(seq, ATT(states_of(toks, D, SEED))) if toks else []

    return per_sequence(T.packed(c, "k", "text"), run, DIGEST)


@query("base_recurrent", f"with {S.STATES}, n as (select seq_id, max(pos) as last from st group by 1) select st.seq_id, {', '.join(f'round(sum(vec[{j + 1}] * pow(0.5, last - pos)), 6) + 0.0 as h{j}' for j in range(4))} from st join n using (seq_id) group by 1")
def base_recurrent(spark, sf):
    def run(seq, toks):
        if not toks:
            return []
        h = K.recurrent(states_of(toks, D, SEED), 0.5)[-1]
        return {"seq_id": seq} | {f"h{j}": float(h[j]) for j in range(4)}

    out = per_sequence(docs_packed(spark, sf), run, "seq_id long, h0 double, h1 double, h2 double, h3 double")
    return out.select("seq_id", *((F.round(f"h{j}", 6) + 0.0).alias(f"h{j}") for j in range(4)))


SELECT = rf"""with g as (select d.doc_id, b.item_id, list_distinct(regexp_split_to_array(trim(lower(b.text)), '\s+')) as q, regexp_split_to_array(trim(lower(d.text)), '\s+') as t from {GOLD}),
  w as (select doc_id, item_id, q, k::int as win, t[k * 224 + 1:k * 224 + 256] as t, len(list_intersect(t[k * 224 + 1:k * 224 + 256], q))::int as score from (select *, unnest(range((len(t) + 223) // 224)) as k from g)),
  rk as (select *, row_number() over (partition by doc_id, item_id order by score desc, win) as r from w)"""


def _read_sql(src: str) -> str:
    """src (doc_id, item_id, win, q, t): what attention of the question's words reads in t."""
    return f"""qs as (select doc_id, item_id, win, qtok, {S.hash_vec('qtok')} as vec from (select doc_id, item_id, win, unnest(q) as qtok from {src})), ts as (select doc_id, item_id, win, {S.hash_vec('tok')} as vec from (select doc_id, item_id, win, unnest(t) as tok from {src})),
  e as (select doc_id, item_id, win, qtok, exp(list_dot_product(qs.vec, ts.vec) * {SCALE!r}) as e, ts.vec[1] as v1, ts.vec[2] as v2 from qs join ts using (doc_id, item_id, win)),
  o as (select doc_id, item_id, win, qtok, sum(e * v1) / sum(e) as o1, sum(e * v2) / sum(e) as o2 from e group by 1, 2, 3, 4), rd as (select doc_id, item_id, win, round(sum(o1), 4) + 0.0 as s0, round(sum(o2), 4) + 0.0 as s1 from o group by 1, 2, 3)"""


def _scored_windows(spark, sf):
    g = gold_pairs(spark, sf).select("doc_id", "item_id", F.array_distinct(words("passage")).alias("q"), words("text").alias("t"))
    w = g.withColumn("win", F.explode(F.sequence(F.lit(0), F.ceil(F.size("t") / 224).cast("int") - 1)))
    w = w.withColumn("t", F.slice("t", F.col("win") * 224 + 1, F.lit(256))).withColumn("score", F.size(F.array_intersect("t", "q")))
    return w.withColumn("r", F.row_number().over(Window.partitionBy("doc_id", "item_id").orderBy(F.desc("score"), "win")))


def _read(rows, keep):
    """rows (doc_id, item_id, q, t and keep) with s0, s1: attention of the question over the words that were kept."""
    import pyarrow as pa
    from pyspark.sql.types import StructType

    kept = rows.select("q", "t", *keep)

    def run(batches):
        for b in batches:
            out = [K.attention(states_of(q, D, SEED), states_of(t, D, SEED), SCALE).sum(0) for q, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns[2:], *(pa.array([round(float(h[j]), 4) + 0.0 for h in out], pa.float64()) for j in (0, 1))], [*keep, "s0", "s1"])

    return kept.mapInArrow(run, StructType([kept.schema[k] for k in keep]).add("s0", "double").add("s1", "double"))


@query("base_select_then_read", f"{SELECT}, sel as (select * from rk where r <= 2), {_read_sql('sel')} select doc_id, item_id, win, score, r::int as r, s0, s1 from sel join rd using (doc_id, item_id, win)")
def base_select_then_read(spark, sf):
    """The cheap filter picks the two windows that share most distinct words with the question; these are read densely."""
    return _read(_scored_windows(spark, sf).filter("r <= 2"), ["doc_id", "item_id", "win", "score", "r"])


@query("base_select_threshold", f"{SELECT}, sel as (select * from rk where score >= 0.6 * len(q)), {_read_sql('sel')} select doc_id, item_id, win, score, s0, s1 from sel join rd using (doc_id, item_id, win)")
def base_select_threshold(spark, sf):
    """All windows that share at least 0.6 of the question's words are read; others count as noise."""
    return _read(_scored_windows(spark, sf).filter(F.col("score") >= 0.6 * F.size("q")), ["doc_id", "item_id", "win", "score"])


@query("base_select_concat", f"{SELECT}, sel as (select doc_id, item_id, 0 as win, any_value(q) as q, flatten(list(t order by win)) as t, sum(score)::bigint as score from rk where r <= 2 group by 1, 2), {_read_sql('sel')} select doc_id, item_id, score, s0, s1 from sel join rd using (doc_id, item_id)")
def base_select_concat(spark, sf):
    """The two best windows become one sequence, which is read at once."""
    w = _scored_windows(spark, sf).filter("r <= 2").groupBy("doc_id", "item_id").agg(F.first("q").alias("q"), F.array_sort(F.collect_list(F.struct("win", "t"))).alias("w"), F.sum("score").cast("long").alias("score"))
    return _read(w.withColumn("t", F.flatten(F.transform("w", lambda x: x["t"]))), ["doc_id", "item_id", "score"])


@query("base_question_attention", rf"""with g as (select d.doc_id, b.item_id, regexp_split_to_array(trim(lower(b.text)), '\s+') as q, regexp_split_to_array(trim(lower(d.text)), '\s+') as t from {GOLD}),
  qs as (select doc_id, item_id, {S.hash_vec('tok')} as vec from (select doc_id, item_id, unnest(q) as tok from g)), ts as (select doc_id, item_id, i, {S.hash_vec('tok')} as vec from (select doc_id, item_id, unnest(t) as tok, generate_subscripts(t, 1) as i from g)),
  a as (select ts.doc_id, ts.item_id, i, exp(list_dot_product(ts.vec, qs.vec) * {SCALE!r}) as e, qs.vec[1] as v1, qs.vec[2] as v2 from ts join qs using (doc_id, item_id)),
  o as (select doc_id, item_id, i, sum(e * v1) / sum(e) as o1, sum(e * v2) / sum(e) as o2 from a group by 1, 2, 3) select doc_id, item_id, count(*) as n, round(sum(o1), 4) + 0.0 as s0, round(sum(o2), 4) + 0.0 as s1 from o group by 1, 2""")
def base_question_attention(spark, sf):
    import pyarrow as pa

    g = gold_pairs(spark, sf).select("doc_id", "item_id", words("passage").alias("q"), words("text").alias("t"))

    def run(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                h = K.attention(states_of(r["t"], D, SEED), states_of(r["q"], D, SEED), SCALE).sum(0)
                out.append((r["doc_id"], r["item_id"], len(r["t"]), round(float(h[0]), 4) + 0.0, round(float(h[1]), 4) + 0.0))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], ["doc_id", "item_id", "n", "s0", "s1"])

    return g.mapInArrow(run, "doc_id long, item_id long, n long, s0 double, s1 double")


HEADS = rf"""with {PARAS}, pt as (select page_id, para_id, list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '') as t from pa),
  tk as (select page_id, para_id, unnest(t) as tok, generate_subscripts(t, 1) - 1 as i from pt), v as (select *, {S.hash_vec('tok')} as vec from tk),
  s as (select page_id, para_id, i, list_dot_product(vec, {HEAD}::double[]) as head, list_dot_product(vec, {QUESTION}::double[]) as start from v),
  p as (select page_id, para_id, max(case when i = 0 then head end) as para, max(start) as best, arg_min(i, (-start, i)) as "at" from s group by 1, 2)"""


def para_scores(spark, sf):
    t = page_paras(spark, sf).select("seq_id", "para_id", F.posexplode(words("text")).alias("i", "tok"))
    v = T.embed(t, D, SEED)
    s = v.select("seq_id", "para_id", "i", dot("vec", F.array(*map(F.lit, HEAD))).alias("head"), dot("vec", F.array(*map(F.lit, QUESTION))).alias("start"))
    best = F.max(F.struct("start", (-F.col("i")).alias("i"))).alias("b")
    p = s.groupBy("seq_id", "para_id").agg(F.max(F.when(F.col("i") == 0, F.col("head"))).alias("para"), best)
    return p.select("seq_id", "para_id", "para", F.col("b.start").alias("best"), (-F.col("b.i")).alias("at"))


def _best(df, score):
    r = F.row_number().over(Window.partitionBy("seq_id").orderBy(F.desc(score), "para_id"))
    return df.withColumn("r", r).filter("r = 1")


@query("base_pipeline_reader", f"""{HEADS} select page_id as seq_id, para_id, "at"::int as "at", round(best, 6) + 0.0 as score from (select *, row_number() over (partition by page_id order by para desc, para_id) as r from p) where r = 1""")
def base_pipeline_reader(spark, sf):
    return _best(para_scores(spark, sf), "para").select("seq_id", "para_id", "at", (F.round("best", 6) + 0.0).alias("score"))


@query("base_joint_reader", f"""{HEADS} select page_id as seq_id, para_id, "at"::int as "at", round(para + best, 6) + 0.0 as score from (select *, row_number() over (partition by page_id order by para + best desc, para_id) as r from p) where r = 1""")
def base_joint_reader(spark, sf):
    p = para_scores(spark, sf).withColumn("s", F.col("para") + F.col("best"))
    return _best(p, "s").select("seq_id", "para_id", "at", (F.round("s", 6) + 0.0).alias("score"))


_fused("base_global_tokens", f"""with {S.STATES}, g as (select *, pos % 64 = 0 as head from st),
  pr as (select a.seq_id, a.pos, a.vec as av, b.vec as bv from g a join g b on a.seq_id = b.seq_id where a.head
    union all select a.seq_id, a.pos, a.vec, b.vec from g a join g b on a.seq_id = b.seq_id where not a.head and b.head
    union all select a.seq_id, a.pos, a.vec, b.vec from (select *, unnest([pos // 64 - 1, pos // 64, pos // 64 + 1]) as k from g where not head) a join (select *, pos // 64 as k from g where not head) b on a.seq_id = b.seq_id and a.k = b.k where abs(a.pos - b.pos) <= 32),
  e as (select seq_id, pos, exp(list_dot_product(av, bv) * {SCALE!r}) as e, bv[1] as v1, bv[2] as v2, bv[3] as v3, bv[4] as v4 from pr), o as (select seq_id, pos, {', '.join(f'sum(e * v{j}) / sum(e) as o{j}' for j in range(1, 5))} from e group by 1, 2) {S.digest('o')}""",
  lambda x: K.global_rows(x, np.arange(0, len(x), 64), 32, SCALE))


@query("base_cascaded", f"""{HEADS.replace('p as (select page_id, para_id, max', 'unused as (select page_id, para_id, max')}, c as (select page_id, para_id, avg(head) as para, arg_min(i, (-start, i)) as "at" from s group by 1, 2)
  select page_id as seq_id, para_id, "at"::int as "at", round(para, 6) + 0.0 as score from (select *, row_number() over (partition by page_id order by para desc, para_id) as r from c) where r = 1""")
def base_cascaded(spark, sf):
    """Paragraph pooling first, then the span in the paragraph whose mean state scores best."""
    t = T.embed(page_paras(spark, sf).select("seq_id", "para_id", F.posexplode(words("text")).alias("i", "tok")), D, SEED)
    s = t.select("seq_id", "para_id", "i", dot("vec", F.array(*map(F.lit, HEAD))).alias("h"), dot("vec", F.array(*map(F.lit, QUESTION))).alias("q"))
    p = s.groupBy("seq_id", "para_id").agg(F.avg("h").alias("para"), F.max(F.struct("q", (-F.col("i")).alias("i"))).alias("b"))
    return _best(p, "para").select("seq_id", "para_id", (-F.col("b.i")).cast("int").alias("at"), (F.round("para", 6) + 0.0).alias("score"))


for _kind in ("cluster", "same_position", "random_hash", "local"):

    @query(f"stack_{_kind}")
    def _stack(spark, sf, kind=_kind):
        """The same depths of the same stack, another layer in their place."""
        plan = LayerPlan.local(4) if kind == "local" else fitted_stack(spark, sf, LayerPlan.explicit([2, 4], n_layers=4, kind=kind))
        return per_sequence(docs_packed(spark, sf), lambda seq, toks: plan.digest(seq, toks), DIGEST)


