"""File sources and sinks. Schemas are always given; nothing is inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DOCUMENT = "doc_id long, text string, lang string, source string"


def read_crawl_json(spark: SparkSession, path: str, schema: str = DOCUMENT) -> DataFrame:
    """JSON lines; lines that don't parse are kept in _corrupt_record."""
    return spark.read.schema(schema + ", _corrupt_record string").json(path)


def read_text_files(spark: SparkSession, path: str) -> DataFrame:
    """One document a file, named by its path."""
    return spark.read.text(path, wholetext=True).select(F.xxhash64(F.col("_metadata.file_path")).alias("doc_id"), F.col("value").alias("text"), F.col("_metadata.file_path").alias("source"))


def read_html_files(spark: SparkSession, path: str, charset: str = "UTF-8") -> DataFrame:
    files = spark.read.format("binaryFile").load(path)
    return files.select(F.xxhash64("path").alias("page_id"), F.col("path").alias("url"), F.decode("content", charset).alias("html"))


def read_lake_table(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.csv(path, header=True, schema=schema)


def read_database(spark: SparkSession, url: str, query: str, **options: str) -> DataFrame:
    return spark.read.format("jdbc").options(url=url, query=query, **options).load()


def write_examples(examples: DataFrame, path: str, rows: int = 1_000_000) -> None:
    """Parquet by chapter and task. Rows are dealt out evenly within each, so that one large task isn't one file."""
    examples.withColumn("shard", F.pmod(F.xxhash64("example_id"), F.lit(64))).repartition("chapter", "task", "shard").drop("shard").write.option("maxRecordsPerFile", rows).partitionBy("chapter", "task").parquet(path)


def write_for_trainer(plan: DataFrame, path: str, partitions: int) -> None:
    """JSON lines in training order: shard names sort as the plan does."""
    from ..plans.curriculum import ordered

    ordered(plan, partitions).write.json(path, compression="gzip")


def write_table_bucketed(df: DataFrame, table: str, column: str, buckets: int) -> None:
    """For joins on ``column`` without a shuffle."""
    df.write.bucketBy(buckets, column).sortBy(column).saveAsTable(table)
