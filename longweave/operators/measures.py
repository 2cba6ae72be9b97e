"""Answer measures as columns and aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def exact_match(pred, gold) -> Column:
    return (F.coalesce(pred, F.lit("")) == F.coalesce(gold, F.lit(""))).cast("int")


def token_f1(pred, gold) -> Column:
    """Bag-of-words F1 of two strings of single spaces; 1 where both are null, 0 where one is."""
    p, g = F.split(pred, " "), F.split(gold, " ")
    count = lambda a, w: F.size(F.filter(a, lambda x: x == w))
    both = F.aggregate(F.array_distinct(p), F.lit(0), lambda s, w: s + F.least(count(p, w), count(g, w)))
    own = 2.0 * both / (F.size(p) + F.size(g))
    p_null, g_null = F.col(pred).isNull(), F.col(gold).isNull()
    return F.when(p_null & g_null, 1.0).when(p_null | g_null, 0.0).otherwise(own)


def answer_prf(answers: DataFrame, wrong_counts_as_fn: bool = False) -> DataFrame:
    """(tp, fp, fn, f1, p, r) of pred and gold, either of which may be null (no answer)."""
    wrong = F.col("pred").isNotNull() & (F.col("gold").isNull() | (F.col("pred") != F.col("gold")))
    missed = F.col("pred").isNull() & F.col("gold").isNotNull()
    if wrong_counts_as_fn:
        missed = missed | (wrong & F.col("gold").isNotNull())
    n = answers.agg(F.count_if(F.col("pred") == F.col("gold")).alias("tp"), F.count_if(wrong).alias("fp"), F.count_if(missed).alias("fn"))
    part = lambda a, b: F.round(a / F.nullif(b, F.lit(0)), 6)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return n.select("tp", "fp", "fn", part(2.0 * tp, 2 * tp + fp + fn).alias("f1"), part(tp, tp + fp).alias("p"), part(tp, tp + fn).alias("r"))


def perplexity(p, weight="1") -> Column:
    """exp of the mean negative log of p, an aggregate; weight: how often each row stands."""
    w = F.expr(weight) if isinstance(weight, str) else weight
    return F.exp(F.sum(-F.ln(p) * w) / F.sum(w))


def bits(p, weight="1") -> Column:
    """Mean negative binary log of p."""
    w = F.expr(weight) if isinstance(weight, str) else weight
    return F.sum(-F.log2(p) * w) / F.sum(w)
