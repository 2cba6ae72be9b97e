"""Token sequences: tokenise, states, questions, paragraphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from longweave.functions.text import words
from longweave.functions.vectors import hash_state


def tokenize(df: DataFrame, id_col: str, text_col: str, unit: str = "word") -> DataFrame:
    """(seq_id, pos, tok), one row per token; unit char takes every character as it is."""
    toks = words(text_col) if unit == "word" else F.regexp_extract_all(F.coalesce(F.col(text_col), F.lit("")), F.lit("(?s)."), F.lit(0))
    return df.select(F.col(id_col).alias("seq_id"), F.posexplode(toks).alias("pos", "tok"))


def packed(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(seq_id, toks), one row per sequence: what kernels read."""
    return df.select(F.col(id_col).alias("seq_id"), words(text_col).alias("toks"))


def vocabulary(tokens: DataFrame, d: int = 8, seed: int = 7) -> DataFrame:
    return tokens.select("tok").distinct().withColumn("vec", hash_state("tok", d, seed))


def embed(tokens: DataFrame, d: int = 8, seed: int = 7) -> DataFrame:
    """States of tokens, made in place: no join, so frequent words skew nothing."""
    return tokens.withColumn("vec", hash_state("tok", d, seed))


def truncate(tokens: DataFrame, mode: str = "infer", train: int = 5000, infer: int = 10_000) -> DataFrame:
    return tokens.filter(F.col("pos") < (train if mode == "train" else infer))


def assemble_context(paras: DataFrame, key: str = "seq_id", order: str = "para_id", text: str = "text", sentinel: str = "<s>") -> DataFrame:
    """One context per key: paragraphs in order, a sentinel before each."""
    parts = F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), words(text).alias("t"))))
    return paras.groupBy(key).agg(F.flatten(F.transform(parts, lambda p: F.concat(F.array(F.lit(sentinel)), p["t"]))).alias("toks"))
