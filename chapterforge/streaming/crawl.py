"""Structured Streaming forms: filter and route arriving documents, monitor rates, sessions, records by type."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import filtering, qa


def route_stream(docs: DataFrame, model: filtering.BayesModel, sink: str, checkpoint: str, keep_at: int = 4, available_now: bool = True):
    """Kept documents of each micro-batch, routed, into Parquet under their batch's name: a batch that runs again replaces its own files."""

    def one(batch: DataFrame, batch_id: int) -> None:
        kept = filtering.apply_filter(batch, model, keep_at)
        qa.route_documents(qa.flag_markers(kept)).write.mode("overwrite").parquet(f"{sink}/batch={batch_id}")

    writer = docs.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer.trigger(processingTime="1 minute")).start()


def zoned(events: DataFrame, column: str = "ts") -> DataFrame:
    """Watermarks need timestamps with a zone; the session's is UTC."""
    return events.withColumn(column, F.col(column).cast("timestamp"))


def without_repeats(docs: DataFrame, time: str = "ts", late: str = "2 hours") -> DataFrame:
    """Each text once within the watermark, by its hash."""
    return docs.withColumn("text_hash", F.sha2("text", 256)).withWatermark(time, late).dropDuplicatesWithinWatermark(["text_hash"])


def windowed_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    return zoned(events).withWatermark("ts", late).groupBy(F.window("ts", width, slide), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    return zoned(events).withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def joined_within(first: DataFrame, second: DataFrame, key: str = "user_id", within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs of events of a user where the second follows within an hour: an interval join of two streams."""
    a = zoned(first).withWatermark("ts", late).select(F.col(key).alias("k1"), F.col("ts").alias("t1"), F.col("event_id").alias("e1"))
    b = zoned(second).withWatermark("ts", late).select(F.col(key).alias("k2"), F.col("ts").alias("t2"), F.col("event_id").alias("e2"))
    return a.join(b, F.expr(f"k1 = k2 and t2 >= t1 and t2 <= t1 + interval {within}"))


def running_records(events: DataFrame) -> DataFrame:
    """State for each event type: the record so far and how often it was met or beaten; rows of a batch are taken in time order."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best, hits, n = state.get if state.exists else (None, 0, 0)
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        for v in rows["value"]:
            n += 1
            if best is not None and v >= best:
                hits += 1
            best = v if best is None or v > best else best
        state.update((float(best), hits, n))
        yield pd.DataFrame({"event_type": [key[0]], "matches_or_beats": [hits], "n": [n]})

    return events.select("event_type", "ts", "event_id", "value").groupBy("event_type").applyInPandasWithState(
        step, "event_type string, matches_or_beats long, n long", "best double, hits long, n long", "update", "NoTimeout"
    )
