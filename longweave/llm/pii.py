"""Personal data in texts: patterns propose, checksums confirm, context words adjust (DataFrame functions only).

Kinds of the base set: email, ip, card (Luhn), phone.  The method adds iban (mod 97) and ssn (only beside a context word).
Null and empty texts have no spans; repeated rows keep one result each; other columns of the
input pass through (a column named pii is replaced).
All loops in the patterns are possessive or over one character class, so a match needs no recursion and each text is
read a bounded number of times, however long it is.  (?:(?<![...])|\\G) starts a match at the head of a run or where the
last match ended: any later start in that run fails or succeeds alike, so the leftmost matches are the same.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from longweave.llm.common import column, table

#: kind -> (Java pattern, SQL condition on m (the match), its words of context, score without and with such a word)
DIGITS = "regexp_replace(m, '[^0-9]', '')"
LUHN = f"""aggregate(sequence(1, length({DIGITS})), 0, (a, i) -> a +
    case when i % 2 = 1 then cast(substring({DIGITS}, -i, 1) as int)
         else cast(substring('0246813579', cast(substring({DIGITS}, -i, 1) as int) + 1, 1) as int) end) % 10 = 0"""
MOD97 = """aggregate(split(concat(substring(m, 5), substring(m, 1, 4)), ''), 0L, (a, c) ->
    case when c = '' then a when c between '0' and '9' then (a * 10 + cast(c as int)) % 97
         else (a * 100 + ascii(c) - 55) % 97 end) = 1"""
KINDS: dict[str, tuple[str, str, str, float, float]] = {
    "email": (r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "true", "mail|contact|write", 0.9, 0.99),
    "ip": (r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "forall(split(m, '[.]'), p -> length(ltrim('0', p)) <= 3 and cast(concat('0', ltrim('0', p)) as int) <= 255)", "ip|host|server|address|login", 0.6, 0.9),
    "card": (r"[0-9](?:[\x20-]?[0-9])++", f"length({DIGITS}) between 13 and 19 and {LUHN}", "card|visa|credit|pay|cvv", 0.7, 0.97),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", f"length({DIGITS}) between 9 and 15", "phone|tel|call|mobile|fax", 0.6, 0.95),
    "iban": (r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}(?![A-Za-z0-9])", MOD97, "iban|bank|account|konto|compte", 0.85, 0.99),
    "ssn": (r"(?<![0-9-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9-])", "true", "ssn|social|security", 0.2, 0.9),
}
BASE = ("email", "ip", "card", "phone")
CONTEXT = 48
SPAN = "array<struct<kind:string,start:int,end:int,score:double>>"


#: Matches per step of the running sum, so that no array of all of them is copied for each.
STEP = 64


def _found(kind: str) -> Column:
    """Spans of one kind from __hit_<kind> (matches) and __text; the pieces between matches give the places."""
    pattern, holds, words, low, high = KINDS[kind]
    quoted = pattern.replace("\\", "\\\\").replace("'", "\\'")
    hit = f"__hit_{kind}"
    return F.expr(f"""
        case when size({hit}) > 0 then
          filter(
            transform(
              zip_with(
                {hit},
                transform(array(transform(sequence(0, cast((size({hit}) - 1) div {STEP} as int)), b -> slice(
                    zip_with(slice(split(__text, '{quoted}', -1), 1, size({hit})), {hit}, (g, m) -> named_struct('g', length(g), 'm', length(m))), b * {STEP} + 1, {STEP}))),
                  parts -> flatten(zip_with(
                    transform(parts, p -> aggregate(p, named_struct('at', 0, 'out', cast(array() as array<int>)),
                      (a, x) -> named_struct('at', a.at + x.g + x.m, 'out', array_append(a.out, a.at + x.g)), a -> a.out)),
                    aggregate(transform(parts, p -> aggregate(p, 0, (a, x) -> a + x.g + x.m)), named_struct('at', 0, 'out', cast(array() as array<int>)),
                      (a, x) -> named_struct('at', a.at + x, 'out', array_append(a.out, a.at)), a -> a.out),
                    (own, base) -> transform(own, o -> o + base))))[0],
                (m, s) -> named_struct('m', m, 's', s)),
              x -> transform(array(x.m), m -> case when {holds} then
                named_struct('kind', '{kind}', 'start', x.s, 'end', x.s + length(m), 'score',
                  case when lower(substring(__text, greatest(x.s - {CONTEXT}, 0) + 1, least(x.s, {CONTEXT}))) rlike '{words}'
                       then {high}D else {low}D end) end)[0]),
            x -> x is not null and x.score >= 0.5)
        else cast(array() as {SPAN}) end""")


def find_pii(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with pii: array of (kind, start, end, score), by kind as in KINDS, then start; code points, end exclusive."""
    own = docs.drop("pii").withColumn("__text", F.coalesce(column(docs, text, "string"), F.lit("")))
    own = own.withColumns({f"__hit_{k}": F.regexp_extract_all("__text", F.lit(p[0]), F.lit(0)) for k, p in KINDS.items()})
    return own.withColumn("pii", F.concat(*map(_found, KINDS))).drop("__text", *(f"__hit_{k}" for k in KINDS))


def redact(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with every span of pii replaced by its kind in angle brackets (overlaps: the earlier span wins)."""
    return find_pii(docs, text).withColumn(text, F.coalesce(F.col(text).cast("string"), F.lit(""))).withColumn(
        text,
        F.expr(f"""aggregate(array_sort(transform(pii, x -> named_struct('start', x.start, 'end', x.end, 'kind', x.kind))),
            named_struct('at', 0, 'out', ''), (a, x) -> case when x.start < a.at then a else
              named_struct('at', x.end, 'out', concat(a.out, substring(`{text}`, a.at + 1, x.start - a.at), '<', x.kind, '>')) end,
            a -> concat(a.out, substring(`{text}`, a.at + 1)))"""),
    )


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    listed = "array_join(transform({}, x -> concat_ws(':', x.kind, x.start, x.end)), ',')"
    base = "filter(pii, x -> x.kind in ('email', 'ip', 'card', 'phone'))"
    return find_pii(docs).select(
        "doc_id",
        *(F.expr(f"cast(size(filter(pii, x -> x.kind = '{k}')) as bigint)").alias(f"n_{k}") for k in BASE),
        F.sha2(F.expr(listed.format(base)), 256).alias("base_sha256"),
        F.expr(listed.format("pii")).alias("spans"),
    )
