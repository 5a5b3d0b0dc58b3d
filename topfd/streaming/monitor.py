"""Watching known dependencies over a stream. Appends can only break a dependency, and raise its redundancy while it holds; so the stream is
monitored and a new discovery is the batch engine's job."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

CONTRADICTION = "lhs_key string, rhs_first string, rhs_now string, at timestamp"


def _keyed(events: DataFrame, lhs: list[str], rhs: str, at: str) -> DataFrame:
    """Left-hand values as one JSON text, nulls kept; the right-hand value as text."""
    return events.select(
        F.to_json(F.struct(*[F.col(c).cast("string").alias(c) for c in lhs]), {"ignoreNullFields": "false"}).alias("lhs_key"), F.col(rhs).cast("string").alias("rhs"), F.col(at).alias("at")
    )


def contradictions(events: DataFrame, lhs: list[str], rhs: str, at: str = "ts") -> DataFrame:
    """Streaming: a row for each event whose right-hand value differs from the first one kept for its left-hand side. State: one value a class. Order inside a
    micro-batch is by time and value; across micro-batches it is arrival."""

    def each(key: tuple[str], frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        frames = list(frames)
        rows = frames[0] if len(frames) == 1 else pd.concat(frames)
        values, when, missing = rows["rhs"].to_numpy(object), rows["at"].to_numpy(), rows["rhs"].isna().to_numpy()
        if state.exists:
            first = state.get[0]
        else:
            unknown = np.isnat(when)
            earliest = unknown if unknown.any() else when == when.min()
            first = None if missing[earliest].any() else min(values[earliest])
            state.update((first,))
        found = np.flatnonzero(~missing if first is None else missing | (values != first))
        found = found[np.argsort(when[found], kind="stable")]
        yield pd.DataFrame({"lhs_key": key[0], "rhs_first": first, "rhs_now": np.where(missing, None, values)[found], "at": when[found]}, columns=["lhs_key", "rhs_first", "rhs_now", "at"])

    grouped = _keyed(events, lhs, rhs, at).groupBy("lhs_key")
    return grouped.applyInPandasWithState(each, CONTRADICTION, "first string", "append", GroupStateTimeout.NoTimeout)


def contradictions_batch(events: DataFrame, lhs: list[str], rhs: str, at: str = "ts") -> DataFrame:
    """The same over a table, in time order."""
    keyed = _keyed(events, lhs, rhs, at)
    first = keyed.groupBy("lhs_key").agg(F.min(F.struct("at", F.col("rhs").isNotNull().alias("some"), "rhs")).alias("f")).select(F.col("lhs_key").alias("k"), F.col("f.rhs").alias("rhs_first"))
    return keyed.join(first, F.col("lhs_key") == F.col("k")).where(~F.col("rhs").eqNullSafe(F.col("rhs_first"))).select("lhs_key", "rhs_first", F.col("rhs").alias("rhs_now"), "at")


def class_sizes(events: DataFrame, attrs: list[str], at: str = "ts", late: str = "1 hour", window: str = "1 day", slide: str | None = None, gap: str | None = None) -> DataFrame:
    """Class sizes in tumbling windows, sliding ones (slide) or sessions (gap), for streams and tables alike; rows later than the watermark are dropped by a stream."""
    marked = events.withWatermark(at, late) if events.isStreaming else events
    span = F.session_window(at, gap) if gap else F.window(at, window, slide) if slide else F.window(at, window)
    return marked.groupBy(span.alias("span"), *attrs).agg(F.count(F.lit(1)).alias("size")).select(F.col("span.start").alias("start"), F.col("span.end").alias("end"), *attrs, "size")


def distinct_events(events: DataFrame, keys: list[str], at: str = "ts", late: str = "1 hour") -> DataFrame:
    """First arrivals of each key within the watermark."""
    return events.withWatermark(at, late).dropDuplicatesWithinWatermark(keys) if events.isStreaming else events.dropDuplicates(keys)


def card_keeper(path: str, attrs: list[str], then: Callable[[DataFrame], None] | None = None) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: keeps the distinct values of an attribute set as Parquet, one folder a micro-batch; a repeated batch overwrites its own. Read them with kept_card."""

    def merge(batch: DataFrame, epoch: int) -> None:
        batch.select(*attrs).distinct().write.mode("overwrite").parquet(f"{path}/epoch={epoch}")
        if then is not None:
            then(batch)

    return merge


def kept_card(spark, path: str, attrs: list[str]) -> int:
    return spark.read.parquet(path).select(*attrs).distinct().count()


#: Whether a stream may run a batch without rows, which lets the watermark close windows and drop expired state.
CLOSING = "spark.sql.streaming.noDataMicroBatches.enabled"


def drain(df: DataFrame, table: str, checkpoint: str, mode: str = "append", closing: bool = True) -> DataFrame:
    """Runs a streaming frame over all that is available and gives its rows, also as the temporary view `table`. Appended rows, as many as the stream has, go to Parquet
    files beside the checkpoint; a complete result, which the stream's state holds anyway, goes to a memory table.

    closing: after the last rows, run the batch that closes windows. Where rows leave as they arrive it gives none, but holds the state a second time."""
    spark, rows = df.sparkSession, f"{checkpoint}-rows"
    sink = df.writeStream.format("parquet").option("path", rows) if mode == "append" else df.writeStream.format("memory").queryName(table)
    before = spark.conf.get(CLOSING)
    spark.conf.set(CLOSING, str(closing and before.lower() == "true").lower())
    try:
        # a stream takes the session's settings as it starts
        q = sink.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    finally:
        spark.conf.set(CLOSING, before)
    try:
        q.awaitTermination()
    finally:
        q.stop()
    if mode == "append":
        spark.read.schema(df.schema).parquet(rows).createOrReplaceTempView(table)
    return spark.table(table)
