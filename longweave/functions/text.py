"""Texts: words, normal answers, paragraphs of HTML."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def words(c) -> Column:
    """Lower-cased words split at white space; an empty text has none."""
    c = F.col(c) if isinstance(c, str) else c
    return F.filter(F.split(F.trim(F.lower(F.coalesce(c, F.lit("")))), r"\s+"), lambda x: x != "")


def normal_answer(c) -> Column:
    """Lower case, no punctuation, no English articles, single spaces."""
    c = F.col(c) if isinstance(c, str) else c
    plain = F.regexp_replace(F.lower(F.coalesce(c, F.lit(""))), r"[!-/:-@\[-`{-~]", "")
    return F.array_join(F.filter(F.split(plain, r"\s+"), lambda w: ~w.isin("", "a", "an", "the")), " ")


def visible_html(c) -> Column:
    """HTML without comments, scripts and styles (scripts may hold literal paragraph tags)."""
    c = F.col(c) if isinstance(c, str) else c
    return F.regexp_replace(F.coalesce(c, F.lit("")), r"(?is)<!--.*?-->|<script.*?</script>|<style.*?</style>", " ")


def paragraphs(c) -> Column:
    """Texts of the p elements, tags and common entities gone."""
    inner = F.regexp_extract_all(visible_html(c), F.lit(r"(?is)<p(?:\s[^>]*)?>(.*?)</p>"), F.lit(1))
    bare = lambda x: F.regexp_replace(x, r"(?s)<[^>]*>", " ")
    entity = lambda x: F.replace(F.replace(F.replace(F.replace(x, F.lit("&lt;"), F.lit("<")), F.lit("&gt;"), F.lit(">")), F.lit("&quot;"), F.lit('"')), F.lit("&amp;"), F.lit("&"))
    return F.transform(inner, lambda x: F.trim(F.regexp_replace(entity(bare(x)), r"\s+", " ")))
