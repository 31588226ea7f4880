"""Helpers that every operator of this subpackage shares."""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN_FOLDERS: list = []


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``. Where that is unset, a temporary one, and that only on a local
    master, whose executors share the driver's disk; on a cluster an error says what to set."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    folder = tempfile.mkdtemp(prefix="chapterforge-")
    spark.sparkContext.setCheckpointDir(folder)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may be gone at exit; the folder is scratch space either way
        pass


def new_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that no other run uses; removed when the driver ends."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _OWN_FOLDERS.append((spark, path))
    return path


@atexit.register
def _clean() -> None:
    for spark, path in _OWN_FOLDERS:
        _delete(spark, path)


def written(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` in the shared folder and read it back: lineage ends there, so lost executors repeat nothing before it."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: rows of a table that may be broadcast; beyond it, joins shuffle
BROADCAST_ROWS = 1_000_000


def small(df: DataFrame) -> DataFrame:
    """For a join: broadcast if a count shows that it has few rows, as it is otherwise. Call it on written tables."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def without_ids(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """``docs`` without the rows whose doc_id is in the only column of ``ids``; null is an id like others."""
    gone = small(written(ids.select(F.col(ids.columns[0]).cast("long").alias("__gone_id")).distinct(), "gone-ids"))
    return docs.join(gone, F.col("doc_id").cast("long").eqNullSafe(F.col("__gone_id")), "left_anti")


def fold(id_column: str = "doc_id", folds: int = 5) -> Column:
    """crc32 of the id as text, modulo ``folds``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(id_column).cast("string"), F.lit("")).cast("binary")) % folds


def rows_of(df: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """Only id and text, under fixed names: other columns can't clash. A null text is the empty one."""
    return df.select(
        F.col(id_column).cast("long").alias("doc_id"),
        F.coalesce(F.col(text_column).cast("string"), F.lit("")).alias("text"),
    )


def arrow_batches(spark: SparkSession, rows: int = 512, megabytes: int = 4) -> None:
    """Keep Arrow batches small, by rows and by bytes, for very long texts; session settings that may change at any time."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(megabytes << 20))


def frugal(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A pass over batches that hands freed memory back to the system when it ends: Python workers live on after a task."""

    def passed(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            hand_back()

    return passed


def hand_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only glibc has it
    if trim:
        trim(0)
