"""Session settings the engine expects where it may choose them."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def build_session(app: str = "chapterforge", master: str | None = None, **settings: str) -> SparkSession:
    """A session with UTC time (given timestamps have no zone) and adaptive execution. Settings given win."""
    wanted = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.parquet.compression.codec": "zstd",
    } | settings
    builder = SparkSession.builder.appName(app)
    return (builder.master(master) if master else builder).config(map=wanted).getOrCreate()


def settled(df: DataFrame, name: str) -> DataFrame:
    """``df`` written in the folder ``spark.checkpoint.dir`` names and read back, so that lineage ends there. Where that is unset, a
    temporary folder, on a local master alone."""
    spark = df.sparkSession
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            folder = held.get()
        elif spark.sparkContext.master.startswith("local"):
            spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="chapterforge-"))
            folder = spark.sparkContext._jsc.sc().getCheckpointDir().get()
        else:
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    path = f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
