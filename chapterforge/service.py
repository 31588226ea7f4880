"""The model boundary: one call shape for rules, recorded answers and remote models."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Protocol

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.text import count_tokens

ROLES = ("rate", "extract", "synthesize", "judge_complete", "judge_accurate", "rate_schema", "write_scenario", "judge_scenario", "describe_row", "entail", "write_page_question", "write_choice", "answer")


class LanguageService(Protocol):
    def complete(self, requests: DataFrame) -> DataFrame:
        """requests: req_id, role, prompt. Returns req_id, response, n_in, n_out."""


def request_key() -> Column:
    """Same role and prompt, same answer."""
    return F.sha2(F.concat_ws("|", "role", "prompt"), 256)


def _counted(answered: DataFrame) -> DataFrame:
    return answered.select("req_id", "response", count_tokens(F.col("prompt")).alias("n_in"), count_tokens(F.col("response")).alias("n_out"))


class RuleService:
    """An expression of the prompt for each role; stays in the JVM."""

    def __init__(self, rules: dict[str, Callable[[Column], Column]]):
        self.rules = rules

    def complete(self, requests: DataFrame) -> DataFrame:
        response = F.lit(None).cast("string")
        for role, rule in self.rules.items():
            response = F.when(F.col("role") == role, rule(F.col("prompt"))).otherwise(response)
        return _counted(requests.withColumn("response", response.cast("string")))


class RecordedService:
    """Replays stored answers (key, response); also stands for human reviewers. What was never recorded is null."""

    def __init__(self, recorded: DataFrame):
        self.recorded = recorded.select("key", "response").dropDuplicates(["key"])

    def complete(self, requests: DataFrame) -> DataFrame:
        return _counted(requests.withColumn("key", request_key()).join(self.recorded, "key", "left"))


class RemoteService:
    """Calls ``fn(role, prompts) -> responses`` for batches of distinct prompts that a cache lacks, and appends what it answers to that
    cache: a Parquet folder by request hash. A run that stops goes on where the cache ends; failures are tried ``tries`` times."""

    def __init__(self, fn: Callable[[str, list[str]], list[str]], cache: str, tries: int = 3):
        self.fn, self.cache, self.tries = fn, cache, tries

    def _cached(self, spark) -> DataFrame:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.cache)
        there = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)
        return spark.read.schema("key string, response string").parquet(self.cache) if there else spark.createDataFrame([], "key string, response string")

    def complete(self, requests: DataFrame) -> DataFrame:
        spark, fn, tries = requests.sparkSession, self.fn, self.tries
        keyed = requests.withColumn("key", request_key())
        missing = keyed.select("key", "role", "prompt").dropDuplicates(["key"]).join(self._cached(spark).select("key"), "key", "left_anti")

        def call(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows, answers = batch.to_pylist(), {}
                for role in sorted({r["role"] for r in rows}):
                    some = [r for r in rows if r["role"] == role]
                    for k in range(tries):
                        try:
                            answers |= {r["key"]: a for r, a in zip(some, fn(role, [r["prompt"] for r in some]), strict=True)}
                            break
                        except Exception:
                            if k + 1 == tries:
                                raise
                yield pa.RecordBatch.from_pylist([{"key": k, "response": v} for k, v in answers.items()], schema=pa.schema([("key", pa.string()), ("response", pa.string())]))

        missing.mapInArrow(call, "key string, response string").write.mode("append").parquet(self.cache)
        return _counted(keyed.join(self._cached(spark).dropDuplicates(["key"]), "key", "left"))


def cost_report(calls: DataFrame, by: list[str]) -> DataFrame:
    """calls: role or stage, n_in, n_out. Model calls and tokens."""
    return calls.groupBy(*by).agg(F.count("*").alias("calls"), F.sum("n_in").alias("tokens_in"), F.sum("n_out").alias("tokens_out"))
