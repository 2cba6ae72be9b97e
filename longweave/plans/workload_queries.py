"""Measures, and the experiments on the given tables."""

from __future__ import annotations

import math
import time

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from longweave.functions import kernels as K
from longweave.functions.text import normal_answer, words
from longweave.functions.vectors import cosine, l2_distance
from longweave.operators import clusters as C
from longweave.operators import tokens as T
from longweave.operators.fused import per_sequence, states_of
from longweave.operators.refresh import Refresh, fit_stack
from longweave.plans import sqltext as S
from longweave.plans.method_queries import BLOCK, D, GOLD, LABELLED, PARAS, SCALE, SEED, docs_packed, gold_pairs, labelled, page_paras, several_snapshots, text_centroids, text_snapshots, vec_chain, vec_ranked, vec_states, window_layer
from longweave.plans.registry import QUERIES, query
from longweave.plans.stack import LayerPlan
from longweave.session import load, persist_cut

# ---------------------------------------------------------------- phrase answers
PHRASE = r"""bq as (select item_id, regexp_split_to_array(trim(lower(text)), '\s+') as t from benchmark),
q as (select item_id, t[1:len(t) - 3] as q, array_to_string(t[len(t) - 2:], ' ') as answer from bq),
dt as (select doc_id, regexp_split_to_array(trim(lower(text)), '\s+') as t from documents),
dsh as (select doc_id, i, t, t[i] || ' ' || t[i + 1] || ' ' || t[i + 2] as sh from (select doc_id, t, unnest(range(1, len(t) - 1)) as i from dt)),
qsh as (select distinct item_id, q[i] || ' ' || q[i + 1] || ' ' || q[i + 2] as sh from (select item_id, q, unnest(range(1, len(q) - 1)) as i from q)),
hit as (select item_id, doc_id, count(distinct sh) as score from dsh join qsh using (sh) group by 1, 2),
top as (select * from (select *, row_number() over (partition by item_id order by score desc, doc_id) as r from hit) where r <= 10),
tail as (select item_id, q[len(q) - 2] || ' ' || q[len(q) - 1] || ' ' || q[len(q)] as sh from q),
cand as (select tail.item_id, array_to_string(dsh.t[i + 3:i + 5], ' ') as pred, row_number() over (partition by tail.item_id order by top.r, i) as k from tail join dsh using (sh) join top on top.item_id = tail.item_id and top.doc_id = dsh.doc_id),
gold as (select item_id, max(1) as has from """ + GOLD + r""" group by 1),
ans as (select q.item_id, nullif(c.pred, '') as pred, case when g.has = 1 then q.answer end as gold from q left join (select * from cand where k = 1) c using (item_id) left join gold g using (item_id))"""


def _shingles(df, key, col):
    t = df.select(key, F.posexplode(F.transform(F.sequence(F.lit(1), F.size(col) - 2), lambda i: F.concat_ws(" ", F.slice(col, i, 3)))).alias("i", "sh"), col)
    return t.withColumn("i", F.col("i") + 1)


def phrase_answers(spark, sf):
    """Retrieval by distinct three-word shingles, ten documents a question; the reader takes what follows the question."""
    q = load(spark, sf, "benchmark").select("item_id", F.col("text").alias("passage"), words("text").alias("t"))
    q = q.select("item_id", "passage", F.expr("slice(t, 1, size(t) - 3)").alias("q"), F.concat_ws(" ", F.expr("slice(t, size(t) - 2, 3)")).alias("answer"))
    docs = load(spark, sf, "documents").select("doc_id", "text")
    dsh = _shingles(docs.select("doc_id", words("text").alias("t")).filter(F.size("t") > 2), "doc_id", "t")
    qsh = _shingles(q.select("item_id", "q").filter(F.size("q") > 2), "item_id", "q").select("item_id", "sh").distinct()
    hit = dsh.select("doc_id", "sh").join(qsh, "sh").groupBy("item_id", "doc_id").agg(F.count_distinct("sh").alias("score"))
    top = hit.withColumn("r", F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("score"), "doc_id"))).filter("r <= 10")
    tail = q.select("item_id", F.concat_ws(" ", F.expr("slice(q, size(q) - 2, 3)")).alias("sh"))
    cand = dsh.join(tail, "sh").join(top, ["item_id", "doc_id"])
    first = F.row_number().over(Window.partitionBy("item_id").orderBy("r", "i"))
    pred = cand.withColumn("k", first).filter("k = 1").select("item_id", F.nullif(F.concat_ws(" ", F.expr("slice(t, i + 3, 3)")), F.lit("")).alias("pred"))
    gold = gold_pairs(spark, sf).select("item_id").distinct().withColumn("has", F.lit(1))
    return q.join(pred, "item_id", "left").join(gold, "item_id", "left").select("item_id", "pred", F.when(F.col("has") == 1, F.col("answer")).alias("gold"))




@query("w_phrase_qa", f"with {PHRASE} select item_id, pred, gold from ans")
def w_phrase_qa(spark, sf):
    return phrase_answers(spark, sf)


NORM = r"array_to_string(list_filter(regexp_split_to_array(regexp_replace(lower(coalesce({x}, '')), '[!-/:-@\[-`{{-~]', '', 'g'), '\s+'), lambda w: w not in ('', 'a', 'an', 'the')), ' ')"
#: Two answers count: the three words, and the last two of them.
GOLDS = f"""golds as (select item_id, {NORM.format(x='pred')} as p, case when gold is null then [''] else [{NORM.format(x='gold')}, {NORM.format(x="array_to_string(string_split(gold, ' ')[2:], ' ')")}] end as g from ans)"""


def normal_golds(answers):
    """(item_id, p, g): the answer and all answers that count, in normal form; '' is no answer."""
    short = F.concat_ws(" ", F.expr("slice(split(gold, ' '), 2, 100)"))
    return answers.select("item_id", normal_answer("pred").alias("p"), F.when(F.col("gold").isNull(), F.array(F.lit(""))).otherwise(F.array(normal_answer("gold"), normal_answer(short))).alias("g"))


@query("m_exact_match", f"with {PHRASE}, {GOLDS} select count(*) as n, round(100 * avg(case when list_contains(g, p) then 1 else 0 end), 6) as em from golds")
def m_exact_match(spark, sf):
    """The normal form of the answer equals that of any that counts."""
    return normal_golds(phrase_answers(spark, sf)).agg(F.count("*").alias("n"), F.round(100 * F.avg(F.array_contains("g", F.col("p")).cast("int")), 6).alias("em"))


@query("m_token_f1", f"""with {PHRASE}, {GOLDS}, x as (select item_id, k, string_split(p, ' ') as p, string_split(g[k], ' ') as g from (select *, unnest(range(1, len(g) + 1)) as k from golds)),
  o as (select item_id, k, p, g, list_sum(list_transform(list_distinct(p), lambda w: least(len(list_filter(p, lambda y: y = w)), len(list_filter(g, lambda y: y = w))))) as o from x),
  f as (select item_id, max(case when p = [''] or g = [''] then (p = g)::int else 2.0 * o / (len(p) + len(g)) end) as f1 from o group by 1) select count(*) as n, round(100 * avg(f1), 6) as f1 from f""")
def m_token_f1(spark, sf):
    """Bag-of-words F1 of normal forms, the best of the answers that count."""
    from longweave.operators.measures import token_f1

    each = normal_golds(phrase_answers(spark, sf)).select("item_id", "p", F.explode("g").alias("g"))
    none = (F.col("p") == "") | (F.col("g") == "")
    f1 = F.when(none, (F.col("p") == F.col("g")).cast("double")).otherwise(token_f1("p", "g"))
    return each.groupBy("item_id").agg(F.max(f1).alias("f1")).agg(F.count("*").alias("n"), F.round(100 * F.avg("f1"), 6).alias("f1"))


PRF = "round(2.0 * tp / nullif(2 * tp + fp + fn, 0), 6) as f1, round(tp * 1.0 / nullif(tp + fp, 0), 6) as p, round(tp * 1.0 / nullif(tp + fn, 0), 6) as r"


def prf_sql(src: str) -> str:
    return f"select tp, fp, fn, {PRF} from (select count(*) filter (where pred = gold) as tp, count(*) filter (where pred is not null and (gold is null or pred <> gold)) as fp, count(*) filter (where pred is null and gold is not null) as fn from {src})"


@query("m_answer_prf", f"with {PHRASE} {prf_sql('ans')}")
def m_answer_prf(spark, sf):
    from longweave.operators.measures import answer_prf

    return answer_prf(phrase_answers(spark, sf))


@query("m_answer_prf_strict", f"with {PHRASE} {prf_sql('ans').replace('pred is null and gold is not null', 'gold is not null and (pred is null or pred <> gold)')}")
def m_answer_prf_strict(spark, sf):
    """A wrong answer where there is one counts as missed, too."""
    from longweave.operators.measures import answer_prf

    return answer_prf(phrase_answers(spark, sf), wrong_counts_as_fn=True)


@query("w_dialog_qa", r"""with c as (select *, regexp_split_to_array(trim(lower(text)), '\s+') as t from conversations),
  q as (select u.conv_id, u.turn, u.t as q, array_to_string(a.t[1:3], ' ') as gold from c u left join c a on a.conv_id = u.conv_id and a.turn = u.turn + 1 and a.role = 'assistant' where u.role = 'user'),
  e as (select x.conv_id, x.turn, y.gold as pred, row_number() over (partition by x.conv_id, x.turn order by len(list_intersect(list_distinct(x.q), list_distinct(y.q))) desc, y.turn) as r from q x join q y on x.conv_id = y.conv_id and y.turn < x.turn and y.gold is not null)
  select q.conv_id, q.turn, e.pred, q.gold from q left join (select * from e where r = 1) e on e.conv_id = q.conv_id and e.turn = q.turn""")
def w_dialog_qa(spark, sf):
    """A user turn is answered as the most alike earlier one was, conversation by conversation."""
    c = load(spark, sf, "conversations").select("conv_id", "turn", "role", words("text").alias("t"))
    nxt = Window.partitionBy("conv_id").orderBy("turn")
    lead = F.when((F.lead("role").over(nxt) == "assistant") & (F.lead("turn").over(nxt) == F.col("turn") + 1), F.concat_ws(" ", F.slice(F.lead("t").over(nxt), 1, 3)))
    q = c.withColumn("gold", lead).filter("role = 'user'").select("conv_id", "turn", F.array_distinct("t").alias("q"), "gold")
    asked = q.select("conv_id", "turn", F.explode("q").alias("w"))
    known = q.filter("gold is not null").select("conv_id", F.col("turn").alias("t"), F.explode("q").alias("w"))
    shared = asked.join(known, ["conv_id", "w"]).filter("t < turn").groupBy("conv_id", "turn", "t").agg(F.count("*").alias("s"))
    best = shared.groupBy("conv_id", "turn").agg(F.min(F.struct((-F.col("s")).alias("s"), "t")).alias("b")).select("conv_id", "turn", F.col("b.t").alias("t"))
    # a turn that shares no word with an earlier one takes the first of them
    first = q.filter("gold is not null").groupBy("conv_id").agg(F.min("turn").alias("first"))
    of = q.select("conv_id", "turn", "gold").join(best, ["conv_id", "turn"], "left").join(first, "conv_id", "left")
    of = of.withColumn("t", F.coalesce("t", F.when(F.col("first") < F.col("turn"), F.col("first"))))
    answer = q.filter("gold is not null").select("conv_id", F.col("turn").alias("t"), F.col("gold").alias("pred"))
    return of.join(answer, ["conv_id", "t"], "left").select("conv_id", "turn", "pred", "gold")


LONG = rf"""with {PARAS}, tp as (select page_id, para_id, list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '') as t from pa), np as (select page_id, count(*) as n from pa group by 1), all_n as (select count(*) as n from pages),
  src as (select p.page_id, case when p.page_id % 2 = 0 then p.page_id else (p.page_id * 7 + 3) % (select n from all_n) end as s from np p),
  qs as (select src.page_id, src.s, (s % np.n)::int as para from src join np on np.page_id = src.s), q as (select qs.page_id, qs.s, qs.para, list_distinct(t[1:8]) as q from qs join tp on tp.page_id = qs.s and tp.para_id = qs.para),
  sc as (select q.page_id, tp.para_id, len(list_intersect(list_distinct(tp.t), q.q)) as score, len(q.q) as n from q join tp on tp.page_id = q.page_id),
  best as (select * from (select *, row_number() over (partition by page_id order by score desc, para_id) as r from sc) where r = 1),
  ans as (select q.page_id, case when best.score >= 0.75 * best.n then best.para_id end as pred, case when q.s = q.page_id then q.para end as gold from q left join best using (page_id))"""


def long_answers(spark, sf):
    """Paragraph or none; half of the questions come from another page."""
    p = page_paras(spark, sf).select("seq_id", "para_id", words("text").alias("t"))
    n = p.groupBy("seq_id").agg(F.count("*").alias("n"))
    pages = load(spark, sf, "pages").agg(F.count("*").alias("pages"))
    src = n.crossJoin(F.broadcast(pages)).select(F.col("seq_id").alias("page_id"), F.when(F.col("seq_id") % 2 == 0, F.col("seq_id")).otherwise((F.col("seq_id") * 7 + 3) % F.col("pages")).alias("s"))
    qs = src.join(n, F.col("s") == F.col("seq_id")).select("page_id", "s", (F.col("s") % F.col("n")).cast("int").alias("para"))
    q = qs.join(p, (F.col("s") == F.col("seq_id")) & (F.col("para") == F.col("para_id"))).select("page_id", "s", "para", F.array_distinct(F.slice("t", 1, 8)).alias("q"))
    sc = q.join(p, F.col("page_id") == F.col("seq_id")).select("page_id", "s", "para", "para_id", F.size(F.array_intersect("t", "q")).alias("score"), F.size("q").alias("n"))
    best = sc.withColumn("r", F.row_number().over(Window.partitionBy("page_id").orderBy(F.desc("score"), "para_id"))).filter("r = 1")
    return best.select("page_id", F.when(F.col("score") >= 0.75 * F.col("n"), F.col("para_id")).alias("pred"), F.when(F.col("s") == F.col("page_id"), F.col("para")).alias("gold"))


@query("w_long_answer", f"{LONG} {prf_sql('ans')}")
def w_long_answer(spark, sf):
    from longweave.operators.measures import answer_prf

    return answer_prf(long_answers(spark, sf))


@query("w_short_answer", f"{LONG}, sh as (select ans.page_id, array_to_string(a.t[9:11], ' ') as pred, array_to_string(g.t[9:11], ' ') as gold from ans left join tp a on a.page_id = ans.page_id and a.para_id = ans.pred left join tp g on g.page_id = ans.page_id and g.para_id = ans.gold) {prf_sql('sh')}")
def w_short_answer(spark, sf):
    """The three words after the question, within the chosen paragraph."""
    from longweave.operators.measures import answer_prf

    p = page_paras(spark, sf).select("seq_id", "para_id", F.concat_ws(" ", F.slice(words("text"), 9, 3)).alias("w"))
    a, g = p.toDF("pa", "ppa", "wa"), p.toDF("pg", "ppg", "wg")
    j = long_answers(spark, sf).join(a, (F.col("pa") == F.col("page_id")) & (F.col("ppa") == F.col("pred")), "left").join(g, (F.col("pg") == F.col("page_id")) & (F.col("ppg") == F.col("gold")), "left")
    return answer_prf(j.select(F.col("wa").alias("pred"), F.col("wg").alias("gold")))


# ---------------------------------------------------------------- language models
FOLD = "('0x' || substr(md5(doc_id::varchar), 1, 8))::bigint % 100 < 5"
@query("w_word_lm", f"""{LABELLED}, tk as (select tok.*, lab.block, lag(tok) over (partition by tok.seq_id order by tok.pos) as prev, seq_id in (select doc_id from documents where {FOLD}) as held from tok join lab using (seq_id, pos)),
  uni as (select tok, count(*) as c from tk where not held group by 1), bi as (select prev, tok, count(*) as c from tk where not held and prev is not null group by 1, 2), tot as (select sum(c) as n, count(*) as v from uni),
  ev as (select *, count(*) over (partition by seq_id, tok order by pos range between 256 preceding and 1 preceding) as near, row_number() over (partition by seq_id, block, tok order by pos) - 1 as far from tk where held),
  p as (select 0.5 * (coalesce(bi.c, 0) + 0.1) / (coalesce(u1.c, 0) + 0.1 * v) + 0.3 * (coalesce(u2.c, 0) + 1) / (n + v) as base, near, far from ev cross join tot left join bi on bi.prev = ev.prev and bi.tok = ev.tok left join uni u1 on u1.tok = ev.prev left join uni u2 on u2.tok = ev.tok)
  select count(*) as n, round(exp(avg(-ln(base + 0.2 * near / 256))), 3) as local_ppl, round(exp(avg(-ln(base + 0.1 * near / 256 + 0.1 * far / {BLOCK}))), 3) as cluster_ppl from p""")
def w_word_lm(spark, sf):
    """Bigrams and unigrams of the training documents, and what the window (or window and block) held before."""
    fold = F.conv(F.substring(F.md5(F.col("seq_id").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 5
    t = labelled(spark, sf).withColumn("held", fold).withColumn("prev", F.lag("tok").over(Window.partitionBy("seq_id").orderBy("pos")))
    t = persist_cut(t)
    train = t.filter("not held")
    uni = train.groupBy("tok").agg(F.count("*").alias("c"))
    bi = train.filter("prev is not null").groupBy("prev", "tok").agg(F.count("*").alias("cb"))
    tot = uni.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    near = F.count("*").over(Window.partitionBy("seq_id", "tok").orderBy("pos").rangeBetween(-256, -1))
    far = F.row_number().over(Window.partitionBy("seq_id", "block", "tok").orderBy("pos")) - 1
    ev = t.filter("held").withColumns({"near": near, "far": far}).crossJoin(F.broadcast(tot))  # tot is one row
    ev = ev.join(bi, ["prev", "tok"], "left").join(uni.toDF("prev", "c1"), "prev", "left").join(uni.toDF("tok", "c2"), "tok", "left").na.fill(0, ["cb", "c1", "c2"])
    base = 0.5 * (F.col("cb") + 0.1) / (F.col("c1") + 0.1 * F.col("v")) + 0.3 * (F.col("c2") + 1) / (F.col("n") + F.col("v"))
    ppl = lambda p: F.round(F.exp(F.avg(-F.ln(p))), 3)
    return ev.agg(F.count("*").alias("n"), ppl(base + 0.2 * F.col("near") / 256).alias("local_ppl"), ppl(base + 0.1 * F.col("near") / 256 + 0.1 * F.col("far") / BLOCK).alias("cluster_ppl"))


CHARS = f"with ch as (select doc_id, {FOLD} as held, regexp_extract_all(text, '(?s).') as c from documents), g as (select held, c[i - 1] as a, c[i] as b from (select held, c, unnest(range(2, len(c) + 1)) as i from ch))"


@query("w_char_lm", f"{CHARS}, bi as (select a, b, count(*) as n from g where not held group by 1, 2), un as (select a, sum(n) as n from bi group by 1), v as (select count(distinct b) as v from bi), e as (select a, b, count(*) as k from g where held group by 1, 2) select sum(k)::bigint as n, round(sum(k * -ln((coalesce(bi.n, 0) + 1) / (coalesce(un.n, 0) + v))) / sum(k) / ln(2), 4) as bpc from e cross join v left join bi using (a, b) left join un using (a)")
def w_char_lm(spark, sf):
    held = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 5
    d = load(spark, sf, "documents").select(held.alias("held"), F.regexp_extract_all("text", F.lit("(?s)."), F.lit(0)).alias("c"))
    g = d.select("held", F.explode(F.expr("transform(sequence(2, greatest(size(c), 2)), i -> struct(c[i - 2] as a, get(c, i - 1) as b))")).alias("x")).select("held", "x.*").filter("b is not null")
    n = persist_cut(g.groupBy("held", "a", "b").agg(F.count("*").alias("k")))
    bi = n.filter("not held").select("a", "b", F.col("k").alias("n"))
    un = bi.groupBy("a").agg(F.sum("n").alias("na"))
    v = bi.agg(F.count_distinct("b").alias("v"))
    e = n.filter("held").join(bi, ["a", "b"], "left").join(un, "a", "left").crossJoin(F.broadcast(v)).na.fill(0, ["n", "na"])
    return e.agg(F.sum("k").alias("n"), F.round(F.sum(F.col("k") * -F.ln((F.col("n") + 1) / (F.col("na") + F.col("v")))) / F.sum("k") / math.log(2), 4).alias("bpc"))


HELD_UNI = f"{S.TOK}, f as (select seq_id, tok, {FOLD.replace('doc_id', 'seq_id')} as held from tok), u as (select tok, count(*) as c from f where not held group by 1), t as (select sum(c) as n, count(*) as v from u)"


@query("m_perplexity", f"with {HELD_UNI} select count(*) as n, round(exp(avg(-ln((coalesce(u.c, 0) + 1) / (t.n + t.v)))), 4) as ppl from f cross join t left join u using (tok) where held")
def m_perplexity(spark, sf):
    """Perplexity of held-out documents under word counts of the others: what any context has to beat."""
    from longweave.operators.measures import perplexity

    fold = F.conv(F.substring(F.md5(F.col("seq_id").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 5
    n = docs_packed(spark, sf).select(fold.alias("held"), F.explode("toks").alias("tok")).groupBy("held", "tok").agg(F.count("*").alias("c"))
    u = n.filter("not held").select("tok", "c")
    k = n.filter("held").select("tok", F.col("c").alias("k"))
    t = u.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    e = k.join(u, "tok", "left").crossJoin(F.broadcast(t))  # one row
    return e.agg(F.sum("k").alias("n"), F.round(perplexity((F.coalesce("c", F.lit(0)) + 1) / (F.col("n") + F.col("v")), "k"), 4).alias("ppl"))


@query("m_bpc", f"{CHARS}, u as (select b, count(*) as c from g where not held group by 1), t as (select sum(c) as n, count(*) as v from u), e as (select b, count(*) as k from g where held group by 1) select sum(k)::bigint as n, round(sum(k * -ln((coalesce(c, 0) + 1) / (n + v))) / sum(k) / ln(2), 4) as bpc from e cross join t left join u using (b)")
def m_bpc(spark, sf):
    """Bits for each character (but the first of a text) under character counts of the other documents."""
    from longweave.operators.measures import bits

    held = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 5
    c = F.slice(F.regexp_extract_all("text", F.lit("(?s)."), F.lit(0)), 2, 2_000_000_000)
    n = load(spark, sf, "documents").select(held.alias("held"), F.explode(c).alias("b")).groupBy("held", "b").agg(F.count("*").alias("c"))
    u = n.filter("not held").select("b", "c")
    t = u.agg(F.sum("c").alias("n"), F.count("*").alias("v"))
    e = n.filter("held").select("b", F.col("c").alias("k")).join(u, "b", "left").crossJoin(F.broadcast(t))  # one row
    return e.agg(F.sum("k").alias("n"), F.round(bits((F.coalesce("c", F.lit(0)) + 1) / (F.col("n") + F.col("v")), "k"), 4).alias("bpc"))


# ---------------------------------------------------------------- measures
@query("m_dataset_stats", r"""with l as (select 'documents' as t, len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) as n from documents union all select 'benchmark', len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) from benchmark union all select 'conversations', len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) from conversations) select t as "table", count(*) as rows_n, median(n) as mid, max(n)::int as longest from l group by t""")
def m_dataset_stats(spark, sf):
    out = None
    for t in ("documents", "benchmark", "conversations"):
        part = load(spark, sf, t).select(F.lit(t).alias("table"), F.size(words("text")).alias("n"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("table").agg(F.count("*").alias("rows_n"), F.median("n").alias("mid"), F.max("n").alias("longest"))


TABLE1 = rf"""with {PARAS}, {S.TOK.replace('tl as', 'dl as').replace('from tl', 'from dl')}, ql as (select 'phrases' as task, b.item_id as k, len(t) as n from (select * from {GOLD}) b join dl on dl.seq_id = b.doc_id),
  cl as (select 'dialogues' as task, conv_id * 1000 + turn as k, sum(n) over (partition by conv_id order by turn) as n, role from (select *, len(list_filter(regexp_split_to_array(trim(lower(coalesce(text, ''))), '\s+'), lambda y: y <> '')) as n from conversations)),
  pl as (select 'pages' as task, page_id as k, (count(*) + sum(len(list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> ''))))::bigint as n from pa group by 2),
  a as (select task, k, n from ql union all select task, k, n from cl where role = 'user' union all select task, k, n from pl)
  select task, count(*) filter (where not held) as train, count(*) filter (where held) as test, round(median(n), 1) as med, max(n)::bigint as longest from (select *, ('0x' || substr(md5(k::varchar), 1, 8))::bigint % 100 < 10 as held from a) group by 1"""


@query("w_dataset_stats", TABLE1)
def w_dataset_stats(spark, sf):
    """Questions for training and testing, median and longest context, for each kind of question here."""
    ctx = T.assemble_context(page_paras(spark, sf)).select(F.lit("pages").alias("task"), F.col("seq_id").alias("k"), F.size("toks").cast("long").alias("n"))
    gold = gold_pairs(spark, sf).select(F.lit("phrases").alias("task"), F.col("item_id").alias("k"), F.size(words("text")).cast("long").alias("n"))
    c = load(spark, sf, "conversations").withColumn("n", F.sum(F.size(words("text"))).over(Window.partitionBy("conv_id").orderBy("turn"))).filter("role = 'user'")
    talk = c.select(F.lit("dialogues").alias("task"), (F.col("conv_id") * 1000 + F.col("turn")).alias("k"), F.col("n").cast("long"))
    held = F.conv(F.substring(F.md5(F.col("k").cast("string")), 1, 8), 16, 10).cast("long") % 100 < 10
    a = ctx.unionByName(gold).unionByName(talk).withColumn("held", held)
    return a.groupBy("task").agg(F.count_if(~F.col("held")).alias("train"), F.count_if("held").alias("test"), F.round(F.median("n"), 1).alias("med"), F.max("n").alias("longest"))


PAIRS = f"with {S.TOK}, x as (select len(t)::bigint as x from tl where len(t) > 0)"


@query("m_attention_pairs", f"""{PAIRS} select sum(x * x)::bigint as dense, sum(list_sum(list_transform(range((x + 223) // 224), lambda k: least(256, x - k * 224) * least(256, x - k * 224))))::bigint as local,
  sum((x // 224) * 224 * 224 + (x % 224) * (x % 224))::bigint as cluster, sum(list_sum(list_transform(range(least(256, x)), lambda r: ((x - r - 1) // 224 + 1) * ((x - r - 1) // 224 + 1))))::bigint as same_position from x""")
def m_attention_pairs(spark, sf):
    """Pairs that each layout reads, from lengths alone."""
    x = docs_packed(spark, sf).select(F.size("toks").cast("long").alias("x")).filter("x > 0")
    local = F.expr("aggregate(transform(sequence(0, cast(ceil(x / 224) as int) - 1), k -> least(256, x - k * 224) * least(256, x - k * 224)), 0L, (a, b) -> a + b)")
    same = F.expr("aggregate(transform(sequence(0L, least(256, x) - 1), r -> ((x - r - 1) div 224 + 1) * ((x - r - 1) div 224 + 1)), 0L, (a, b) -> a + b)")
    return x.agg(F.sum(F.col("x") * F.col("x")).alias("dense"), F.sum(local).alias("local"), F.sum(F.expr("(x div 224) * 224 * 224 + (x % 224) * (x % 224)")).alias("cluster"), F.sum(same).alias("same_position"))


@query("m_delta_table", f"""{PAIRS}, s as (select sum(x * x)::bigint as dense, sum((x // 224) * 224 * 224 + (x % 224) * (x % 224))::bigint as cluster from x) select k as method, round(v * 1.0 / cluster, 6) as to_cluster from (select unnest(['dense', 'cluster']) as k, unnest([dense, cluster]) as v, cluster from s)""")
def m_delta_table(spark, sf):
    return m_attention_pairs(spark, sf).unpivot("cluster", ["dense"], "method", "v").select("method", F.round(F.col("v") / F.col("cluster"), 6).alias("to_cluster")).unionByName(spark.createDataFrame([("cluster", 1.0)], "method string, to_cluster double"))


@query("m_plan_cost")
def m_plan_cost(spark, sf):
    """Physical cost by plan: exchanges, sorts, scans and Python passes of the layer and of its long form."""
    rows = []
    for name in ("cal_text_states", "cal_attn_vectors", "stack_cluster", "w_phrase_qa"):
        plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        rows += [(name, op, plan.count(op)) for op in ("Exchange", "Sort ", "FileScan", "MapInArrow", "BroadcastNestedLoopJoin", "CartesianProduct")]
    return spark.createDataFrame(rows, "query string, operator string, n int")


@query("m_padding_waste", f"{S.vectors_slice()}, s as (select cluster, count(*) as n from asg group by 1) select round(count(*) * max(n) * max(n) / sum(n * n), 6) as waste from s")
def m_padding_waste(spark, sf):
    return QUERIES["cal_padded_cost"](spark, sf).select("waste")


@query("m_cluster_balance", f"{S.vectors_slice()}, s as (select cluster, count(*) as n from asg group by 1), t as (select sum(n) as t from s) select min(n) as lo, median(n) as mid, max(n) as hi, round(-sum(n / t * ln(n / t)), 6) as entropy from s, t")
def m_cluster_balance(spark, sf):
    n = C.nearest(vec_states(spark, sf), vec_chain(spark, sf)).groupBy("cluster").agg(F.count("*").alias("n"))
    p = F.col("n") / F.sum("n").over(Window.partitionBy())
    return n.withColumn("p", p).agg(F.min("n").alias("lo"), F.median("n").alias("mid"), F.max("n").alias("hi"), F.round(-F.sum(F.col("p") * F.ln("p")), 6).alias("entropy"))


#: Fixed list: frequent function words of the four languages of the texts.
STOP = ["the", "of", "and", "to", "in", "a", "is", "it", "on", "by", "de", "la", "el", "que", "en", "y", "los", "le", "et", "les", "des", "un", "une", "der", "die", "das", "und", "den", "von", "zu", "mit", ",", "."]
IN_STOP = ", ".join(f"'{w}'" for w in STOP)
KIND = f"case when tok = '<s>' then 'sentinel' when regexp_matches(tok, '^[0-9][0-9.,:/-]*$') then 'number' when tok in ({IN_STOP}) then 'stop' when regexp_matches(tok, '[@/=_<>{{}}]') then 'code' when regexp_matches(tok, '[^a-z]') then 'marked' else 'word' end"


def token_kind():
    t = F.col("tok")
    return F.when(t == "<s>", "sentinel").when(t.rlike("^[0-9][0-9.,:/-]*$"), "number").when(t.isin(*STOP), "stop").when(t.rlike("[@/=_<>{}]"), "code").when(t.rlike("[^a-z]"), "marked").otherwise("word")


@query("m_type_purity", f"{LABELLED}, k as (select lab.cluster, {KIND} as kind, count(*) as n from tok join lab using (seq_id, pos) group by 1, 2) select cluster::int as cluster, sum(n)::bigint as n, arg_min(kind, (-n, kind)) as kind, round(max(n) / sum(n), 6) as purity from k group by 1")
def m_type_purity(spark, sf):
    k = labelled(spark, sf).groupBy("cluster", token_kind().alias("kind")).agg(F.count("*").alias("c"))
    return k.groupBy("cluster").agg(F.sum("c").alias("n"), F.min(F.struct((-F.col("c")).alias("c"), "kind"))["kind"].alias("kind"), F.round(F.max("c") / F.sum("c"), 6).alias("purity"))


REPORT = f"""{LABELLED}, k as (select lab.cluster, {KIND} as kind, count(*) as n from tok join lab using (seq_id, pos) group by 1, 2), kk as (select cluster, sum(n)::bigint as n, max(n) as top, arg_min(kind, (-n, kind)) as kind from k group by 1),
  wc as (select lab.cluster, tok.tok, count(*) as n from tok join lab using (seq_id, pos) group by 1, 2), tw as (select *, row_number() over (partition by cluster order by n desc, tok) as r from wc),
  longest as (select arg_min(seq_id, (-len(t), seq_id)) as seq_id from tl), ps as (select cluster, pos, row_number() over (partition by cluster order by pos) as r from lab where seq_id = (select seq_id from longest))
  select kk.cluster::int as cluster, kk.n, kk.kind, round(kk.top / kk.n, 6) as purity, w.words, coalesce(p.positions, '') as positions from kk
  join (select cluster, string_agg(tok, ' ' order by r) as words from tw where r <= 12 group by 1) w using (cluster) left join (select cluster, string_agg(pos::varchar, ' ' order by r) as positions from ps where r <= 20 group by 1) p using (cluster)"""


@query("w_cluster_report", REPORT)
def w_cluster_report(spark, sf):
    """Each cluster by its words: what kind they mostly are, the most frequent ones, where they stand in the longest document."""
    from longweave.plans.method_queries import frequent_words

    lab = labelled(spark, sf)
    k = lab.groupBy("cluster", token_kind().alias("kind")).agg(F.count("*").alias("c"))
    kk = k.groupBy("cluster").agg(F.sum("c").alias("n"), F.max("c").alias("top"), F.min(F.struct((-F.col("c")).alias("c"), "kind"))["kind"].alias("kind"))
    inorder = lambda c: F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", c))), lambda x: x[c].cast("string")), " ")
    w = frequent_words(lab, 12).groupBy("cluster").agg(inorder("tok").alias("words"))
    one = docs_packed(spark, sf).select("seq_id", F.size("toks").alias("x")).agg(F.min(F.struct((-F.col("x")).alias("x"), "seq_id"))["seq_id"].alias("seq_id"))
    p = lab.join(F.broadcast(one), "seq_id").withColumn("r", F.row_number().over(Window.partitionBy("cluster").orderBy("pos"))).filter("r <= 20")
    p = p.groupBy("cluster").agg(inorder("pos").alias("positions"))
    return kk.join(w, "cluster").join(p, "cluster", "left").select("cluster", "n", "kind", F.round(F.col("top") / F.col("n"), 6).alias("purity"), "words", F.coalesce("positions", F.lit("")).alias("positions"))


PAGE_STATES = rf"""{PARAS}, ptl as (select page_id as seq_id, flatten(list(list_concat(['<s>'], list_filter(regexp_split_to_array(trim(lower(text)), '\s+'), lambda y: y <> '')) order by para_id)) as t from pa group by 1),
  ptok as (select seq_id, unnest(t) as tok, (generate_subscripts(t, 1) - 1)::int as pos from ptl), {S.window_states_of('p', 16, 12, SCALE)}, {S.label_states_of('p')}"""


@query("m_sentinel_colocation", f"""{LABELLED}, {PAGE_STATES}, pb as (select seq_id, pos, (row_number() over (partition by seq_id order by cluster, pos) - 1) // {BLOCK} as block from plab0),
  pc as (select pb.seq_id, block, count(*) filter (where tok = '<s>') as c from pb join ptok using (seq_id, pos) group by 1, 2)
  select seq_id, sum(c)::bigint as n, case when sum(c) > 1 then round(sum(c * (c - 1)) / (sum(c) * (sum(c) - 1)), 6) end as share from pc group by 1""")
def m_sentinel_colocation(spark, sf):
    """Share of a page's sentinel pairs that fall into one block, from counts."""
    ctx, cent = T.assemble_context(page_paras(spark, sf)), text_centroids(spark, sf)

    def run(seq, toks):
        blocks = K.blocks_of(K.assign(window_layer(toks), cent), BLOCK)
        here = [sum(toks[i] == "<s>" for i in rows) for rows in blocks]
        n = sum(here)
        return {"seq_id": seq, "n": n, "share": round(sum(c * (c - 1) for c in here) / (n * (n - 1)), 6) if n > 1 else None}

    return per_sequence(ctx, run, "seq_id long, n long, share double")


@query("m_reach", f"{LABELLED}, b as (select seq_id, block, max(pos) - min(pos) as reach from lab group by 1, 2) select count(*) as blocks, max(reach)::int as longest, round(avg(reach), 6) as mean, round(avg(case when reach > 256 then 1 else 0 end), 6) as over_window from b")
def m_reach(spark, sf):
    b = labelled(spark, sf).groupBy("seq_id", "block").agg((F.max("pos") - F.min("pos")).alias("reach"))
    return b.agg(F.count("*").alias("blocks"), F.max("reach").alias("longest"), F.round(F.avg("reach"), 6).alias("mean"), F.round(F.avg(F.when(F.col("reach") > 256, 1).otherwise(0)), 6).alias("over_window"))


@query("m_inertia", f"{S.vectors_slice()} select count(*) as n, round(avg(list_cosine_similarity(a.vec, c.vec)), 6) as mean_cosine, round(sum(list_distance(a.vec, c.vec) * list_distance(a.vec, c.vec)), 4) as inertia from asg a join chain c on c.ord = a.cluster")
def m_inertia(spark, sf):
    c = vec_chain(spark, sf)
    j = C.nearest(vec_states(spark, sf), c).join(F.broadcast(c.select(F.col("ord").alias("cluster"), F.col("vec").alias("cv"))), "cluster")
    d = l2_distance("vec", "cv")
    return j.agg(F.count("*").alias("n"), F.round(F.avg(cosine("vec", "cv")), 6).alias("mean_cosine"), F.round(F.sum(d * d), 4).alias("inertia"))


@query("m_chain_smoothness", f"with recursive {S.CENT}, {S.CHAIN}, a as (select list_cosine_similarity(vec, lag(vec) over (order by ord)) as s from chain), b as (select list_cosine_similarity(vec, lag(vec) over (order by cid)) as s from c) select round((select avg(s) from a), 6) as chained, round((select avg(s) from b), 6) as unordered")
def m_chain_smoothness(spark, sf):
    c = vec_chain(spark, sf)
    step = lambda by: c.withColumn("p", F.lag("vec").over(Window.orderBy(by))).filter("p is not null").agg(F.round(F.avg(cosine("vec", "p")), 6))
    return step("ord").toDF("chained").crossJoin(step("cid").toDF("unordered"))


@query("m_drift", f"""with {S.CENT}, a as (select vec, cid from (select e.vec_id, e.embedding::double[] as vec, c.cid, row_number() over (partition by e.vec_id order by list_distance(e.embedding::double[], c.vec), c.cid) as rn from embeddings e, c) where rn = 1),
  n as (select cid, list(v order by j) as vec from (select cid, j, avg(v) as v from (select cid, unnest(vec) as v, generate_subscripts(vec, 1) as j from a) group by 1, 2) group by 1) select c.cid::int as cid, round(list_distance(c.vec, n.vec), 6) as moved from c join n using (cid)""")
def m_drift(spark, sf):
    """How far each centroid moves in one refresh."""
    means = C.label_means(load(spark, sf, "embeddings"))
    rows = means.orderBy("cid").collect()
    new = C.kmeans_step(vec_states(spark, sf), np.array([r["vec"] for r in rows])).filter("n > 0").select(F.array(*(F.lit(r["cid"]) for r in rows))[F.col("cid")].alias("cid"), F.col("vec").alias("nv"))
    return means.join(new, "cid").select(F.col("cid").cast("int").alias("cid"), F.round(l2_distance("vec", "nv"), 6).alias("moved"))


TURN_STATES = rf"""qtok as (select seq_id, unnest(t) as tok, (generate_subscripts(t, 1) - 1)::int as pos from (select conv_id * 1000 + turn as seq_id, list_filter(regexp_split_to_array(trim(lower(coalesce(text, ''))), '\s+'), lambda y: y <> '') as t from conversations)),
  {S.window_states_of('q', 16, 12, SCALE)}, {S.label_states_of('q')}"""


@query("m_attention_recall", f"""{LABELLED}, {TURN_STATES}, b as (select seq_id, pos, vec, (row_number() over (partition by seq_id order by cluster, pos) - 1) // 8 as block, pos // 8 as place from qlab0),
  t as (select a.block = b.block as same, a.place = b.place as near, row_number() over (partition by a.seq_id, a.pos order by round(list_dot_product(a.vec, b.vec), 6) desc, b.pos) as r from b a join b on a.seq_id = b.seq_id and a.pos <> b.pos)
  select count(*) as pairs, round(avg(same::int), 4) as cluster, round(avg(near::int), 4) as local from t where r <= 4""")
def m_attention_recall(spark, sf):
    """Share of each state's four strongest dense partners in its dialogue turn that its block of eight holds: clustered
    blocks, and plain ones.  A turn is one row, so pairs exist within a kernel only."""
    cent = text_centroids(spark, sf)

    def run(seq, toks):
        if len(toks) < 2:
            return []
        x = window_layer(toks)
        ids = np.empty(len(x), dtype=int)
        for k, rows in enumerate(K.blocks_of(K.assign(x, cent), 8)):
            ids[rows] = k
        plain = np.arange(len(x)) // 8
        best = strongest(x, 4)
        return {"n": best.size, "c": int((ids[best] == ids[:, None]).sum()), "l": int((plain[best] == plain[:, None]).sum())}

    got = per_sequence(turns(spark, sf), run, "n long, c long, l long").agg(*(F.sum(k).alias(k) for k in ("n", "c", "l")))
    return got.select(F.col("n").alias("pairs"), F.round(F.col("c") / F.col("n"), 4).alias("cluster"), F.round(F.col("l") / F.col("n"), 4).alias("local"))


# ---------------------------------------------------------------- experiments without SQL
def turns(spark, sf):
    return T.packed(load(spark, sf, "conversations").withColumn("k", F.col("conv_id") * 1000 + F.col("turn")), "k", "text")


#: Partners of a row are looked through in so many groups first, whose largest tell how strong one must be.
GROUPS = 64


def strongest(x, top):
    """Numbers of each row's strongest partners by dot product to six digits (ties: the smaller), a bounded number of rows at
    a time.  Products in single precision tell which can be among them; those are made again in double precision."""
    (n, d), out = x.shape, []
    k, step = min(top, n - 1), max(32, 4 * K.AT_ONCE // n)
    large = float(np.einsum("ij,ij->i", x, x).max())
    kind = np.float32 if large < 1e6 else np.float64
    y, slack = x.astype(kind), 4 * (d + 8) * float(np.finfo(kind).eps) * large + 2e-6  # of two products, and of six digits
    for at in range(0, n, step):
        s = y @ np.ascontiguousarray(y[at : at + step].T)  # partners by rows
        m = s.shape[1]
        s[np.arange(at, at + m), np.arange(m)] = -np.inf
        if n >= 4 * GROUPS and k <= GROUPS // 4:
            whole = n - n % GROUPS
            tops = s[:whole].reshape(-1, GROUPS * m).max(0).reshape(GROUPS, m)  # k groups hold one as strong as the k-th of these
            least = np.partition(tops, GROUPS - k, 0)[GROUPS - k]
        else:
            least = np.partition(s, n - k, 0)[n - k]
        found = np.flatnonzero((s >= (least - slack).astype(kind)).ravel())
        j, i = np.divmod(found, m)
        order = np.argsort(i, kind="stable")
        i, j = i[order], j[order]
        count = np.bincount(i, minlength=m)
        place = np.arange(len(i)) - np.repeat(np.cumsum(count) - count, count)
        value, number = np.full((m, count.max()), np.inf), np.zeros((m, count.max()), np.int64)
        value[i, place], number[i, place] = -np.round(np.einsum("ij,ij->i", x[j], x[at + i]), 6), j
        out.append(np.take_along_axis(number, np.argsort(value, 1, kind="stable")[:, :k], 1))
    return np.concatenate(out)


def within_groups(x, groups):
    """(outputs of attention within each of groups, the mean where they overlap; the groups of each row, filled up by
    numbers of its own).  Groups of one size go together."""
    out, safe = np.zeros_like(x), float(np.einsum("ij,ij->i", x, x).max()) * SCALE < K.SAFE
    rows, size = np.concatenate(groups), np.array([len(g) for g in groups])
    count = np.bincount(rows, minlength=len(x))
    begin, alone = np.cumsum(size) - size, count.max() == 1
    for length in np.unique(size):
        at = rows[begin[size == length][:, None] + np.arange(length)]
        for some in np.array_split(at, max(1, at.size * int(length) // K.AT_ONCE)):
            h = x[some]
            if safe:
                s = (h * SCALE) @ h.swapaxes(-1, -2)
                np.exp(s, out=s)
                got = s @ h / s.sum(-1, keepdims=True)
            else:
                got = K.attention(h, scale=SCALE)
            if alone:
                out[some] = got
            else:
                np.add.at(out, some, got)
    order = np.argsort(rows, kind="stable")
    place = np.arange(len(rows)) - np.repeat(np.cumsum(count) - count, count)
    ids = np.repeat(-1 - np.arange(len(x))[:, None], count.max(), 1)
    ids[rows[order], place] = np.repeat(np.arange(len(groups)), size)[order]
    return out / count[:, None], ids


def against_dense(x, ways, top=8):
    """For each of ways (lists of groups of rows, which may overlap): recall of the strongest partners and relative error of the
    outputs of attention within its groups; a row's output is the mean over its groups.  The dense side is made once for all."""
    best, full = strongest(x, top), K.attention(x, x, SCALE)
    norm, out = float((full**2).sum()), []
    for groups in ways:
        own, ids = within_groups(x, groups)
        theirs, met = ids[best], False
        for a in range(ids.shape[1]):
            for b in range(ids.shape[1]):
                met = met | (theirs[:, :, a] == ids[:, None, b])
        out.append((float(met.mean()), math.sqrt(float(((own - full) ** 2).sum()) / max(norm, 1e-24))))
    return out


SWAP_WIN, SWAP_STRIDE = 64, 48


def swap_groups(kind, x, centroids=None, directions=None):
    n = len(x)
    if kind == "local":
        return [np.arange(a, z) for a, z in K.window_bounds(n, SWAP_WIN, SWAP_STRIDE)]
    if kind == "same_position":  # rows of equal index in windows of one stride
        return [np.arange(r, n, SWAP_STRIDE) for r in range(min(n, SWAP_STRIDE))]
    return K.blocks_of(K.assign(x, centroids) if kind == "cluster" else K.hash_labels(x, directions), SWAP_STRIDE)


def _swap(spark, sf, kinds, label):
    """Recall and error of each of kinds (name: (kind, centroids, directions)) over all documents: means over those longer than a
    window, and recall over those of more than 1,024 words."""

    def run(seq, toks):
        if len(toks) < 2:
            return []
        x = window_layer(toks)
        got = against_dense(x, [swap_groups(kind, x, cent, dirs) for kind, cent, dirs in kinds.values()])
        return [{label: name, "x": len(x), "recall": recall, "error": error} for name, (recall, error) in zip(kinds, got, strict=True)]

    each = per_sequence(docs_packed(spark, sf).repartition(4 * spark.sparkContext.defaultParallelism, "seq_id"), run, f"{label} {'int' if label == 'p' else 'string'}, x long, recall double, error double")
    far = F.col("x") > SWAP_WIN
    return each.groupBy(label).agg(F.count("*").alias("n"), F.count_if(far).alias("n_long"), F.round(F.avg(F.when(far, F.col("recall"))), 6).alias("recall"), F.round(F.avg(F.when(far, F.col("error"))), 6).alias("error"), F.round(F.avg(F.when(F.col("x") > 1024, F.col("recall"))), 6).alias("recall_1024"))


def swap_kinds(spark, sf):
    dirs = np.random.default_rng(SEED).normal(size=(64, D))
    cent = text_centroids(spark, sf, 64)
    return {k: (k, cent, dirs) for k in ("local", "same_position", "random_hash", "cluster")}


def sweep_kinds(spark, sf):
    ps = (16, 64, 256, 512)
    return {p: ("cluster", snapshots[-1].ordered, None) for p, snapshots in zip(ps, several_snapshots(spark, sf, ps), strict=True)}


@query("w_layer_swap")
def w_layer_swap(spark, sf):
    """The same states of the documents under each kind of layer: windows, equal positions, 64 random directions, 64 fitted
    clusters."""
    return _swap(spark, sf, swap_kinds(spark, sf), "kind")


@query("w_centroid_sweep")
def w_centroid_sweep(spark, sf):
    """More fitted centroids, the same blocks: recall and error against dense attention."""
    return _swap(spark, sf, sweep_kinds(spark, sf), "p")


@query("m_delta_recall")
def m_delta_recall(spark, sf):
    """What each kind of layer changes against windows alone, and each number of centroids against 64; one pass for all."""
    few = {str(p): way for p, way in sweep_kinds(spark, sf).items()}
    both = persist_cut(_swap(spark, sf, swap_kinds(spark, sf) | few, "kind"))
    a, b = both.filter(~F.col("kind").isin(*few)), both.filter(F.col("kind").isin(*few))
    base = a.filter("kind = 'local'").select(F.col("recall").alias("r0"), F.col("error").alias("e0"))
    low = b.filter("kind = '64'").select(F.col("recall").alias("r0"), F.col("error").alias("e0"))
    delta = lambda df, against, to: df.crossJoin(F.broadcast(against)).select(F.col("kind").alias("of"), F.lit(to).alias("against"), F.round(F.col("recall") - F.col("r0"), 6).alias("recall"), F.round(F.col("error") - F.col("e0"), 6).alias("error"))  # noqa: E731  one row
    return delta(a.filter("kind <> 'local'"), base, "local").unionByName(delta(b.filter("kind <> '64'"), low, "64"))


GRID_CONTEXT = 600


def grid_contexts(spark, sf):
    """(item_id, q, t, gold): each question with the document that shares most three-word runs with it, cut to
    GRID_CONTEXT words, and the three words that answer it."""
    q = load(spark, sf, "benchmark").select("item_id", words("text").alias("w")).filter(F.size("w") > 6)
    q = q.select("item_id", F.expr("slice(w, 1, size(w) - 3)").alias("q"), F.concat_ws(" ", F.expr("slice(w, size(w) - 2, 3)")).alias("gold"))
    docs = load(spark, sf, "documents").select("doc_id", words("text").alias("t")).filter(F.size("t") > 2)
    hit = _shingles(docs, "doc_id", "t").select("doc_id", "sh").join(_shingles(q, "item_id", "q").select("item_id", "sh").distinct(), "sh").groupBy("item_id", "doc_id").agg(F.count_distinct("sh").alias("s"))
    best = hit.groupBy("item_id").agg(F.min(F.struct((-F.col("s")).alias("s"), "doc_id"))["doc_id"].alias("doc_id"))
    return q.join(best, "item_id").join(docs, "doc_id").select("item_id", "q", F.slice("t", 1, GRID_CONTEXT).alias("t"), "gold")


def grid_states(toks):
    """States small enough for what 24 layers add to count."""
    return states_of(toks, 8, SEED) / 5 if toks else np.empty((0, 8))


def read_answer(plan, q, t):
    """The words after the place whose state is most like that of the question's last word, in the window's own frame."""
    ctx, qs = plan.encode(grid_states(t), grid_states(q))
    last = qs[:, -1].mean(0)
    near = K.similarity(ctx[:-3], last[None])[:, 0] if len(ctx) > 3 else np.empty(0)
    at = int(near.argmax()) + 1 if len(near) else 0
    return " ".join(t[at : at + 3]), float(near.max()) if len(near) else 0.0


@query("w_layer_grid")
def w_layer_grid(spark, sf):
    """Which depths attend within clusters (divisible by a, at least b, of 24): the share of questions whose answer is
    read, and how far the output lies from that of window layers alone."""
    local = LayerPlan.local(24, win=64, stride=48)
    plans = [(0, 0, local)] + [(a, b, LayerPlan.modulo(a, b, 24, win=64, stride=48)) for a in (3, 4, 5, 6) for b in (8, 12, 16, 20)]
    shared = fit_stack(docs_packed(spark, sf), LayerPlan.explicit([20], win=64, stride=48), grid_states, Refresh(cap=20_000, iterations=1, every=1, steps=4)).fitted.get(20)
    for _, _, plan in plans:  # states differ little between depths: one fit serves all
        plan.fitted.update(dict.fromkeys(plan.cal, shared) if shared is not None else {})
    ctx = grid_contexts(spark, sf).withColumn("part", F.xxhash64("item_id")).repartition(2 * spark.sparkContext.defaultParallelism, "part")

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            out = []
            for item, q, t, gold in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                x, qv, base = grid_states(t), grid_states(q), None
                for a, b, plan in plans:
                    h = plan.run(x, qv)
                    base = h if base is None else base
                    out.append((item, a, b, len(plan.cal), int(read_answer(plan, q, t)[0] == gold), float(np.linalg.norm(h - base) / np.linalg.norm(base))))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], ["item_id", "a", "b", "depths", "hit", "change"])

    each = ctx.select("item_id", "q", "t", "gold").mapInArrow(run, "item_id long, a long, b long, depths long, hit long, change double")
    return each.groupBy("a", "b", "depths").agg(F.count("*").alias("n"), F.round(100 * F.avg("hit"), 4).alias("em"), F.round(F.avg("change"), 6).alias("change"))


@query("w_bank_sweep")
def w_bank_sweep(spark, sf):
    """Banks of two sizes and refreshes at two rates over the stream of documents: how far centroids move at the last
    refresh, and how near validation states lie to them in the end."""
    from longweave.plans.method_queries import valid_fold

    ways = {(cap, every): text_snapshots(spark, sf, 16, Refresh(cap=cap, iterations=4, every=every, steps=4)) for cap in (50_000, 100_000) for every in (2, 4)}
    packed = docs_packed(spark, sf).filter(valid_fold())
    names = list(ways)

    def run(seq, toks):
        x = window_layer(toks) if toks else np.empty((0, D))
        return [{"k": k, "n": len(x), "total": float(K.similarity(x, ways[w][-1].centroids).max(1).sum())} for k, w in enumerate(names)] if len(x) else []

    near = {r["k"]: r["s"] for r in per_sequence(packed, run, "k long, n long, total double").groupBy("k").agg((F.sum("total") / F.sum("n")).alias("s")).collect()}
    rows = [(cap, every, len(ways[cap, every]), round(ways[cap, every][-1].moved, 4), round(near[k], 4) if k in near else None) for k, (cap, every) in enumerate(names)]
    return spark.createDataFrame(rows, "cap int, every int, refreshes int, moved double, cosine double")


def state_bank(spark, sf, cap=100_000):
    """(seq_id, pos, vec): the newest cap states of the stream of documents, 16 wide, after one window layer."""
    from longweave.operators.refresh import newest_sequences

    packed = docs_packed(spark, sf)
    last = packed.agg(F.max("seq_id")).first()[0]
    since = newest_sequences(packed.select("seq_id", F.size("toks").alias("n")), cap, 0, last if last is not None else 0)

    def run(seq, toks):
        return [{"seq_id": seq, "pos": k, "vec": v} for k, v in enumerate(window_layer(toks, 16))] if toks else []

    held = per_sequence(packed.filter(F.col("seq_id") >= since), run, "seq_id long, pos long, vec array<double>")
    return persist_cut(held.orderBy(F.desc("seq_id"), F.desc("pos")).limit(cap))


def bank_rows(bank):
    """(all rows of a bank, whose cap bounds them; its distinct ones in a seeded order, moved apart so that no state lies
    as near to one as to another)."""
    x = np.array([r["vec"] for r in bank.select("vec").collect()])
    each = np.unique(x, axis=0)
    each = each[np.random.default_rng(1).permutation(len(each))]
    return x, each * (1 + 1e-4 * np.arange(len(each)))[:, None]


@query("w_kmeans_time")
def w_kmeans_time(spark, sf):
    """Seconds of one refresh over a bank of document states, by each way; the bank is capped by its own rule."""
    bank = state_bank(spark, sf)
    x, each = bank_rows(bank)
    init, out = each[:64], []
    for name, f in (("lloyd_distributed", lambda: C.kmeans(bank, init, 5)), ("lloyd", lambda: K.kmeans(x, init, 5)), ("bounded", lambda: K.kmeans_bounded(x, init, 5))):
        began = time.perf_counter()
        got = f()
        out.append((name, len(x), round(time.perf_counter() - began, 3), int(got[2]) if isinstance(got, tuple) else None))
    return spark.createDataFrame(out, "way string, n long, seconds double, distances long")


@query("kmeans_bounded")
def kmeans_bounded(spark, sf):
    """Bounded and plain Lloyd from one start over a whole bank of document states: equal labels, fewer distances."""
    x, each = bank_rows(state_bank(spark, sf))
    init = each[:40]
    a, b = K.kmeans(x, init, 10), K.kmeans_bounded(x, init, 10)
    return spark.createDataFrame([(int((a[1] == b[1]).sum()), len(x), a[2], b[2])], "equal long, n long, lloyd_distances long, bounded_distances long")


@query("kmeans_mllib")
def kmeans_mllib(spark, sf):
    """Other clusterings in place of K-Means: sizes and the mean squared distance to the own centre.  The library's mixture takes
    plain densities, which overflow for 64 numbers and near-singular components, so the mixture is our own."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    v = persist_cut(vec_states(spark, sf).select("vec_id", "vec", array_to_vector("vec").alias("features")))
    out, ways = None, {"kmeans": KMeans(k=10, seed=1).fit(v), "bisecting": BisectingKMeans(k=10, seed=1).fit(v)}
    both = {name: way.transform(v).select("prediction", "vec") for name, way in ways.items()}
    both["mixture"] = C.likeliest(v.select("vec"), C.mixture(v.select("vec"), np.array(ways["kmeans"].clusterCenters())))
    for name, got in both.items():
        centre = got.select("prediction", F.posexplode("vec").alias("j", "x")).groupBy("prediction", "j").agg(F.count("*").alias("n"), (F.sum(F.col("x") * F.col("x")) - F.sum("x") * F.sum("x") / F.count("*")).alias("ss"))
        part = centre.groupBy("prediction").agg(F.first("n").alias("n"), F.sum("ss").alias("ss"))
        part = part.agg(F.lit(name).alias("way"), F.count("*").alias("clusters"), F.max("n").alias("largest"), F.round(F.sum("ss") / F.sum("n"), 6).alias("mean_square"))
        out = part if out is None else out.unionByName(part)
    return out.select("way", "clusters", "largest", "mean_square")


LINES = "ls as (select l_suppkey, row_number() over (partition by l_suppkey order by l_shipdate, l_orderkey, l_linenumber) - 1 as pos, [l_quantity / 50, l_discount * 10, l_tax * 10, l_extendedprice / 100000] as vec from lineitem)"


@query("w_line_sequences", f"""with {LINES}, c as (select * from (values (0, [0.2, 0.2, 0.2, 0.2]), (1, [0.8, 0.2, 0.6, 0.6]), (2, [0.5, 0.8, 0.2, 0.4]), (3, [0.9, 0.9, 0.7, 0.8])) t(ord, cv)),
  a as (select l_suppkey, pos, ord from (select ls.l_suppkey, ls.pos, c.ord, row_number() over (partition by l_suppkey, pos order by list_distance(vec, cv::double[]), ord) as rn from ls, c) where rn = 1),
  r as (select *, row_number() over (partition by l_suppkey order by ord, pos) - 1 as srank from a) select l_suppkey, count(*) as n, sum(srank * pos)::bigint as check_sum, count(distinct srank // {BLOCK}) as blocks from r group by 1""")
def w_line_sequences(spark, sf):
    """No text at all: each supplier's lines in time are a sequence of four numbers."""
    w = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber")
    v = F.array(F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("l_extendedprice") / 100000)
    s = load(spark, sf, "lineitem").select(F.col("l_suppkey").alias("seq_id"), (F.row_number().over(w) - 1).alias("hpos"), v.alias("vec"))
    c = spark.createDataFrame([(0, [0.2, 0.2, 0.2, 0.2]), (1, [0.8, 0.2, 0.6, 0.6]), (2, [0.5, 0.8, 0.2, 0.4]), (3, [0.9, 0.9, 0.7, 0.8])], "ord int, vec array<double>")
    r = C.cluster_rank(C.nearest(s, c, "l2"))
    return r.groupBy(F.col("seq_id").alias("l_suppkey")).agg(F.count("*").alias("n"), F.sum((F.col("srank") * F.col("hpos")).cast("long")).alias("check_sum"), F.count_distinct(F.floor(F.col("srank") / BLOCK)).alias("blocks"))


@query("w_vectors_cal", f"{S.vectors_slice()} select vec_id, cluster::int as cluster, srank, (srank // {BLOCK})::int as block from ranked")
def w_vectors_cal(spark, sf):
    return C.chunk(vec_ranked(spark, sf), BLOCK).select("vec_id", "cluster", "srank", "block")


@query("w_quality_head")
def w_quality_head(spark, sf):
    """A head on pooled document states, fitted without a fifth of the documents and judged on these."""
    from longweave.plans.operator_queries import pooled_quality

    p = pooled_quality(spark, sf)
    held = F.col("held")
    right = (F.col("p") >= 0.5) == (F.col("label") >= 0.5)
    return p.groupBy("held").agg(F.count("*").alias("n"), F.round(F.avg(right.cast("int")), 4).alias("accuracy"), F.round(F.avg(F.col("label")), 4).alias("share")).orderBy(held)


@query("w_stream_bank", "select count(*) as held, min(event_id) as oldest, max(event_id) as newest from (select event_id from events order by event_id desc limit 1000)")
def w_stream_bank(spark, sf):
    return QUERIES["stream_bank"](spark, sf).agg(F.count("*").alias("held"), F.min("arrival").alias("oldest"), F.max("arrival").alias("newest"))
