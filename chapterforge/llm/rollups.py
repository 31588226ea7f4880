"""Token counts as rollups that deltas maintain.

A ledger is a folder with a log and data. A batch holds signed changes of additive totals (documents, tokens) by
source, language and tokenizer version, already summed: an insert adds a document and its tokens, a delete takes
them away, a revision adds the difference of two counts.

The log has one small file a version, 1, 2, 3, ..., made in one atomic step that fails if the version is there; what the log
doesn't name doesn't count. A commit writes its data first, under a name of its own, then the next version with the
batch's id. If another writer was first it reads the log again: an id that is there by now changes nothing, otherwise the version
after is tried. A compaction is a version too: it names the sum of all versions up to one of them and the ids they hold.
Totals are the sum of the last compaction and of all commits after what it covers, so a crash between any two steps leaves
either the state before or the state after, and data that no version names. Compaction deletes nothing, so readers keep what
they read; ``vacuum`` does, at a time of one's choice.

Defined results: null texts count as empty, with no tokens; a null source or language is a group of its own; repeated rows count
each; empty batches commit; keys whose changes cancel out have no row in totals; other columns are not read.
"""

from __future__ import annotations

import json
import os
import re
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_batches, frugal, new_path, written
from .tokens import WordIds, tokenizer_path

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, docs long, tokens long"
#: file systems whose rename would replace its goal, where a hard link fails if the goal is there
_LINKS = ("file",)


class Ledger:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._jvm = spark.sparkContext._jvm
        self._hadoop = spark.sparkContext._jsc.hadoopConfiguration()
        self._path = self._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(self._hadoop)
        for part in ("log", "data"):
            self._fs.mkdirs(self._path(f"{self.path}/{part}"))

    # -- the log --

    def _names(self, part: str) -> list[str]:
        return [s.getPath().getName() for s in self._fs.listStatus(self._path(f"{self.path}/{part}"))]

    def _read(self, version: int) -> dict:
        stream = self._fs.open(self._path(f"{self.path}/log/{version:012d}.json"))
        try:
            return json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def _log(self) -> list[dict]:
        """The last compaction, if there is one, and what follows the versions that it covers."""
        versions = sorted((int(n[:-5]) for n in self._names("log") if re.fullmatch(r"\d{12}\.json", n)), reverse=True)
        found, covered = [], 0
        for v in versions:
            if v <= covered:
                break
            entry = self._read(v) | {"version": v}
            if "covers" not in entry:
                found.append(entry)
            elif not covered:
                covered = entry["covers"]
                found.append(entry)
        return found[::-1]

    def _publish(self, version: int, entry: dict) -> bool:
        """Make this version, whole and at once; False if it is there."""
        staged, goal = f"{self.path}/.staged-{uuid.uuid4().hex}", f"{self.path}/log/{version:012d}.json"
        out = self._fs.create(self._path(staged), False)
        out.write(json.dumps(entry).encode())
        out.close()
        try:
            if self._fs.getScheme() in _LINKS:
                local = lambda p: str(self._path(p).toUri().getPath())
                os.link(local(staged), local(goal))
            else:
                kinds = getattr(self._jvm.org.apache.hadoop.fs, "Options$Rename")
                none = self.spark.sparkContext._gateway.new_array(kinds, 1)
                none[0] = kinds.NONE
                self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._path(goal).toUri(), self._hadoop).rename(self._path(staged), self._path(goal), none)
            return True
        except Exception:
            if not self._fs.exists(self._path(goal)):
                raise
            return False
        finally:
            self._fs.delete(self._path(staged), False)

    @staticmethod
    def _ids(log: list[dict]) -> set[str]:
        return {i for e in log for i in ([e["id"]] if "id" in e else e["ids"])}

    def batches(self) -> list[str]:
        """Ids of all committed batches."""
        return sorted(self._ids(self._log()))

    def committed(self, batch_id: str) -> bool:
        return batch_id in self._ids(self._log())

    # -- batches --

    def _store(self, rows: DataFrame) -> str:
        name = uuid.uuid4().hex
        rows.write.parquet(f"{self.path}/data/{name}")  # a row for each key
        return name

    def commit(self, batch_id: str, changes: DataFrame) -> bool:
        """changes: the keys, docs and tokens, signed. False if this id was committed before."""
        if not batch_id:
            raise ValueError("a batch needs an id")
        if self.committed(batch_id):
            return False
        summed = changes.groupBy(*KEYS).agg(F.sum("docs").cast("long").alias("docs"), F.sum("tokens").cast("long").alias("tokens"))
        data = self._store(summed.filter("docs <> 0 or tokens <> 0"))
        while True:
            log = self._log()
            if batch_id in self._ids(log):
                return False  # another writer was first; vacuum takes the data away
            if self._publish(max((e["version"] for e in log), default=0) + 1, {"id": batch_id, "data": data}):
                return True

    def _changes(self, log: list[dict]) -> DataFrame:
        if not log:
            return self.spark.createDataFrame([], SCHEMA)
        return self.spark.read.schema(SCHEMA).parquet(*[f"{self.path}/data/{e['data']}" for e in log])

    def _totals(self, log: list[dict]) -> DataFrame:
        summed = self._changes(log).groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        return summed.filter("docs <> 0 or tokens <> 0")

    def totals(self) -> DataFrame:
        """Totals by source, language and tokenizer; keys whose documents are all gone have no row."""
        return self._totals(self._log())

    def compact(self) -> bool:
        """One batch in place of all that are committed by now. False if there is nothing to sum, or another compaction came first."""
        log = self._log()
        if len(log) < 2:
            return False
        entry = {"covers": max(e["version"] for e in log), "ids": sorted(self._ids(log)), "data": self._store(self._totals(log))}
        while True:
            now = self._log()
            if any("covers" in e and e not in log for e in now):
                return False
            if self._publish(max(e["version"] for e in now) + 1, entry):
                return True

    def vacuum(self) -> int:
        """Delete what the log's last compaction covers, data that no version names, and staged leftovers; the number of data folders.

        For times when no writer is between its two steps and no reader works with totals from before the last compaction.
        """
        log = self._log()
        covered, needed = max((e.get("covers", 0) for e in log), default=0), {e["data"] for e in log}
        unused = [n for n in self._names("data") if n not in needed]
        for path in (
            *[f"log/{n}" for n in self._names("log") if re.fullmatch(r"\d{12}\.json", n) and int(n[:-5]) <= covered],
            *[f"data/{n}" for n in unused],
            *[s.getPath().getName() for s in self._fs.listStatus(self._path(self.path)) if s.getPath().getName().startswith(".staged-")],
        ):
            self._fs.delete(self._path(f"{self.path}/{path}"), True)
        return len(unused)


def signed(counts: DataFrame, sign: int = 1) -> DataFrame:
    """Inserts (or deletes, with -1) of documents with their counts: the keys and n_tokens."""
    return counts.select(*KEYS, F.lit(sign).cast("long").alias("docs"), (F.col("n_tokens") * sign).alias("tokens"))


def revised(before: Column, after: Column, counts: DataFrame) -> DataFrame:
    """Changes of documents that stay, from one count to another."""
    return counts.select(*KEYS, F.lit(0).cast("long").alias("docs"), (after - before).cast("long").alias("tokens"))


def token_counts(docs: DataFrame, path: str | None = None, version: str = "word_bpe_49k", text_column: str = "text") -> DataFrame:
    """doc_id, source, lang, tokenizer, estimate (a quarter of the characters), n_tokens (the tokenizer's) of each row."""
    arrow_batches(docs.sparkSession)
    path = path or tokenizer_path()
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.col("lang").cast("string").alias("lang"),
        F.coalesce(F.col(text_column).cast("string"), F.lit("")).alias("text"),
    )

    def count(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        words = WordIds.shared(path)
        for texts in batches:
            yield pd.Series([len(ids) // 4 for ids in words.each(texts.tolist())], dtype="int64")

    estimate = F.ceil(F.length("text") / 4).cast("long").alias("estimate")
    return rows.select("doc_id", "source", "lang", F.lit(version).alias("tokenizer"), estimate, F.pandas_udf(frugal(count), "long", F.PandasUDFType.SCALAR_ITER)("text").alias("n_tokens"))


def rollup(docs: DataFrame, path: str | None = None, version: str = "word_bpe_49k") -> DataFrame:
    """The whole table through a ledger: all rows enter with estimates, exact counts revise them, all rows enter once more
    and the same rows leave, and each commit is tried twice. The totals are those of exact counts over all rows."""
    spark = docs.sparkSession
    counts = written(token_counts(docs, path, version), "token-counts")
    ledger = Ledger(spark, new_path(spark, "token-ledger"))
    for _ in range(2):
        ledger.commit("1-estimates", signed(counts.withColumn("n_tokens", F.col("estimate"))))
        ledger.commit("2-exact", revised(F.col("estimate"), F.col("n_tokens"), counts))
        ledger.commit("3-again", signed(counts))
        ledger.commit("4-taken", signed(counts, -1))
    ledger.compact()
    return ledger.totals()
