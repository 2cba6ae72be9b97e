"""The training-corpus pipeline: five stages over documents, each on all that the one before kept.

quality (documents judged bad go), line dedup (repeated lines go), near-duplicates (one document of each group stays),
decontamination (documents that hold benchmark passages go), packing (where each piece of each document lies).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from longweave.llm import decontaminate, line_dedup, near_dup, packing, quality
from longweave.llm.common import ship, table
from longweave.llm.files import new_folder


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    ship(spark)
    model = quality.train(docs, table(spark, sf_dir, "labels").select("doc_id", "quality"))
    return quality.score_quality(docs, model).filter("predicted = 1").select(*docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.remove_repeated_lines(docs)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dup.keep_representatives(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("quality", keep_good),
    ("line_dedup", drop_lines),
    ("near_dup", keep_one_of_each),
    ("decontaminate", drop_leaks),
    ("packing", pack),
]

#: Training, sketches and tokenizers are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    folder = new_folder(spark, "pipeline")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
