"""Corpus pipeline over ``documents``: five stages, each a Parquet table that the next one reads.

Toxic documents go; one document of each class of near duplicates stays; documents that hold a benchmark item go; secrets are masked;
what is left is packed into sequences.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from chapterforge.llm import decontamination, neardup, packing, secrets, toxicity
from chapterforge.llm.common import without_ids, written

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose document is predicted toxic go. Of rows that repeat an id, all go if one does; null ids stay."""
    scores = toxicity.score_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return without_ids(docs, scores.filter("predicted = 1 and doc_id is not null").select("doc_id")).select(*COLUMNS)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.keep_one(docs).select(*COLUMNS)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontamination.drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).select(*COLUMNS)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.mask_secrets(docs).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("toxicity", without_toxic),
    ("near duplicates", without_near_copies),
    ("benchmark decontamination", without_benchmark),
    ("secret scan", without_secrets),
    ("best-fit packing", packed),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs, name.replace(" ", "-"))
    return docs


#: learned classifiers and signatures are beyond SQL; tests hold the stages against brute force
ORACLE_SQL = None
