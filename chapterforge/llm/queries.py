"""Queries of this subpackage: name -> (spark, sf_dir) -> DataFrame, and DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import score_toxicity

    return score_toxicity(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op2_url_verdicts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .urls import judge_urls

    return judge_urls(_read(spark, sf_dir, "pages"))


def op3_secret_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .secrets import scan_secrets

    return scan_secrets(_read(spark, sf_dir, "documents"))


def op10_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .rollups import rollup

    return rollup(_read(spark, sf_dir, "documents"))


def op4_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontamination import find_leaks

    return find_leaks(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark"))


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .neardup import find_classes

    return find_classes(_read(spark, sf_dir, "documents"))


def op7_lattice_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .lattice import score_corpus

    return score_corpus(_read(spark, sf_dir, "documents"))


def op8_top_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries: the whole texts of every row whose doc_id is divisible by 50, against all rows."""
    from .topk import search_all

    docs = _read(spark, sf_dir, "documents")
    return search_all(docs, docs.filter("doc_id % 50 = 0"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    return pack_documents(_read(spark, sf_dir, "documents"))


def op5_packed_token_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import packed_matrix

    return packed_matrix(_read(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for k, v in sorted(globals().items()) if k.startswith("op") and k[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    from . import decontamination

    return {"op4_benchmark_leaks": decontamination.ORACLE}
