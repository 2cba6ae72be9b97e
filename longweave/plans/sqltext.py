"""Pieces of reference SQL that several oracles share."""

TOK = r"""tl as (select doc_id as seq_id, list_filter(regexp_split_to_array(trim(lower(coalesce(text, ''))), '\s+'), lambda y: y <> '') as t from documents),
tok as (select seq_id, unnest(t) as tok, (generate_subscripts(t, 1) - 1)::int as pos from tl)"""


def hash_vec(tok: str, d: int = 8, seed: int = 7) -> str:
    return f"list_transform(range({d}), lambda j: ((('0x' || substr(md5({tok} || ':' || j || ':{seed}'), 1, 8))::bigint % 17) - 8)::double)"


STATES = TOK + f""",
voc as (select tok, {hash_vec("tok")} as vec from (select distinct tok from tok)),
st as (select tok.seq_id, tok.pos, voc.vec from tok join voc using (tok))"""

CENT = """ce as (select label as cid, j, avg(v) as v from (select label, unnest(embedding)::double as v, generate_subscripts(embedding, 1) as j from embeddings) group by 1, 2),
c as (select cid, list(v order by j) as vec from ce group by cid)"""

#: Needs c (cid, vec); gives chain (ord, cid, vec).
CHAIN = """chain as (
  select 0 as ord, cid, [cid] as used, vec from c where cid = (select min(cid) from c)
  union all
  select ord + 1, cid, list_append(used, cid), vec from (
    select p.ord, p.used, c.cid, c.vec, row_number() over (order by list_cosine_similarity(p.vec, c.vec) desc, c.cid) as rn
    from chain p, c where not list_contains(p.used, c.cid)) where rn = 1)"""

#: Needs chain; gives asg (vec_id, vec, cluster).
ASSIGN = """asg as (select vec_id, vec, ord as cluster from (
  select e.vec_id, e.embedding::double[] as vec, k.ord, row_number() over (partition by e.vec_id order by {near} desc, k.ord) as rn
  from embeddings e, chain k) where rn = 1)"""
COSINE = "list_cosine_similarity(e.embedding::double[], k.vec)"


def vectors_slice(near: str = COSINE) -> str:
    """with ... up to ranked (vec_id, vec, cluster, srank)."""
    return f"with recursive {CENT}, {CHAIN}, {ASSIGN.format(near=near)}, ranked as (select *, (row_number() over (order by cluster, vec_id) - 1)::int as srank from asg)"


def attention(src: str, group: str, row: str, scale: float, d: int = 4) -> str:
    """(row columns, o1..od): softmax attention among the rows of src that share group."""
    on = " and ".join(f"a.{g} = b.{g}" for g in group.split(", "))
    keys = ", ".join(f"a.{r}" for r in row.split(", "))
    sums = ", ".join(f"sum(e * v{j}) / sum(e) as o{j}" for j in range(1, d + 1))
    vals = ", ".join(f"b.vec[{j}] as v{j}" for j in range(1, d + 1))
    return f"(select {row}, {sums} from (select {keys}, exp(list_dot_product(a.vec, b.vec) * {scale!r}) as e, {vals} from {src} a join {src} b on {on}) group by {row})"


def digest(src: str, digits: int = 4) -> str:
    """Row counts and coordinate sums per seq_id of src (seq_id, o1..o4)."""
    return f"select seq_id, count(*) as n, {', '.join(f'round(sum(o{j + 1}), {digits}) + 0.0 as s{j}' for j in range(4))} from {src} group by seq_id"


def window_states(win: int, stride: int, scale: float, d: int = 8) -> str:
    """CTEs up to hs (seq_id, pos, vec): states after one window layer, overlaps merged by their mean."""
    rows = f"(select *, unnest(range(greatest(0, ceil((pos - {win - 1}) / {stride}.0))::bigint, pos // {stride} + 1)) as win from st)"
    mean = ", ".join(f"avg(o{j})" for j in range(1, d + 1))
    return f"""{STATES}, w as (select * from {rows}), en as {attention("w", "seq_id, win", "seq_id, win, pos", scale, d)},
hs as materialized (select seq_id, pos, [{mean}] as vec from en group by 1, 2)"""


def kmeans_step(bank: str, old: str, new: str, d: int = 8) -> str:
    mean = ", ".join(f"avg(vec[{j}])" for j in range(1, d + 1))
    return f"""{new} as materialized (select o.cid, coalesce(m.vec, o.vec) as vec from {old} o left join (select cid, [{mean}] as vec from (
  select id, any_value(vec) as vec, arg_min(cid, (-s, cid)) as cid from (select b.id, b.vec, k.cid, 2 * list_dot_product(b.vec, k.vec) - list_dot_product(k.vec, k.vec) as s from {bank} b, {old} k) group by id) group by cid) m using (cid))"""


def refreshed(p: int = 16, cap: int = 100_000, iterations: int = 4, every: int = 2, steps: int = 4) -> str:
    """Needs tl and hs; gives the centroids r1, r2 .. of each refresh of one pass, and c, those of the last."""
    out = [
        f"its as (select seq_id, (seq_id * {iterations}) // (mx + 1) + 1 as it from (select seq_id from tl where len(t) > 0) cross join (select max(seq_id) as mx from tl))",
        f"r0 as (select i as cid, list_transform({hash_vec(chr(39) + 'centroid' + chr(39) + ' || i')}, lambda y: y * (1 + 0.0137 * i)::double) as vec from range({p}) r(i))",
    ]
    for r in range(1, iterations // every + 1):
        out.append(f"bank{r} as materialized (select row_number() over () as id, vec from (select vec from hs join its using (seq_id) where it <= {r * every} order by seq_id desc, pos desc limit {cap}))")
        names = [f"r{r - 1}", *(f"r{r}_{k}" for k in range(1, steps)), f"r{r}"]
        out += [kmeans_step(f"bank{r}", a, b) for a, b in zip(names[:-1], names[1:], strict=True)]
    return ",\n".join([*out, f"c as (select cid, vec from r{iterations // every})"])


#: Needs hs and chain; gives lab0 (seq_id, pos, vec, cluster).
LABEL_STATES = """lab0 as materialized (select seq_id, pos, any_value(vec) as vec, arg_min(ord, (-near, ord)) as cluster from (
  select h.seq_id, h.pos, h.vec, k.ord, case when list_dot_product(h.vec, h.vec) = 0 then 0 else list_cosine_similarity(h.vec, k.vec) end as near from hs h, chain k) group by 1, 2)"""


def window_states_of(pre: str, win: int, stride: int, scale: float, d: int = 8) -> str:
    """The same from tokens {pre}tok (seq_id, pos, tok), up to {pre}hs."""
    mean = ", ".join(f"avg(o{j})" for j in range(1, d + 1))
    return f"""{pre}voc as (select tok, {hash_vec("tok")} as vec from (select distinct tok from {pre}tok)), {pre}st as (select k.seq_id, k.pos, v.vec from {pre}tok k join {pre}voc v using (tok)),
{pre}w as (select *, unnest(range(greatest(0, ceil((pos - {win - 1}) / {stride}.0))::bigint, pos // {stride} + 1)) as win from {pre}st), {pre}en as {attention(pre + "w", "seq_id, win", "seq_id, win, pos", scale, d)},
{pre}hs as materialized (select seq_id, pos, [{mean}] as vec from {pre}en group by 1, 2)"""


def label_states_of(pre: str) -> str:
    return LABEL_STATES.replace("lab0", f"{pre}lab0").replace("from hs h", f"from {pre}hs h")
