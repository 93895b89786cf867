"""Monitors: FD checks on streams, and propagation that follows a feed of schema changes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery


def fd_monitor(stream: DataFrame, lhs: list[str], rhs: str, ts: str, watermark: str = "1 hour", window: str = "1 hour", slide: str | None = None) -> DataFrame:
    """window, lhs, n, violated: per window and key, whether rhs took more than one value. State is a minimum, a maximum and counts a key; rows later than the watermark are dropped."""
    value = F.col(rhs)
    broken = (F.count(value) > 0) & ((F.min(value) != F.max(value)) | (F.count(value) < F.count(F.lit(1))))
    frame = F.window(ts, window, slide) if slide else F.window(ts, window)
    return _timed(stream, ts).withWatermark(ts, watermark).groupBy(frame, *lhs).agg(F.count("*").alias("n"), broken.alias("violated"))


def _timed(stream: DataFrame, ts: str) -> DataFrame:
    """The stream with ts as a timestamp: watermarks need one with a zone."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")) if dict(stream.dtypes)[ts] == "timestamp_ntz" else stream


def session_monitor(stream: DataFrame, lhs: list[str], rhs: str, ts: str, watermark: str = "1 hour", gap: str = "30 minutes") -> DataFrame:
    """The same for sessions of a key, which end after a gap."""
    value = F.col(rhs)
    broken = (F.count(value) > 0) & ((F.min(value) != F.max(value)) | (F.count(value) < F.count(F.lit(1))))
    return _timed(stream, ts).withWatermark(ts, watermark).groupBy(F.session_window(ts, gap).alias("window"), *lhs).agg(F.count("*").alias("n"), broken.alias("violated"))


def caught_up(monitor: DataFrame, keys: list[str], folder: str) -> DataFrame:
    """Runs a monitor over all that its stream holds now; the latest state of each key is returned.

    Every micro-batch overwrites its own folder of changed keys, so a batch that is repeated after a failure counts once.
    The same folder goes on where the last run ended.
    """
    spark, rows = monitor.sparkSession, f"{folder}/rows"

    def batch(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{rows}/epoch={epoch}")

    query = monitor.writeStream.outputMode("update").foreachBatch(batch).option("checkpointLocation", f"{folder}/checkpoint")
    query.trigger(availableNow=True).start().awaitTermination()
    found = spark.read.schema(monitor.schema.add("epoch", "long")).parquet(rows)
    rest = [c for c in monitor.columns if c not in keys]
    latest = found.groupBy(*keys).agg(F.max_by(F.struct(*rest), "epoch").alias("state"))
    return latest.select(*keys, *(F.col(f"state.{c}").alias(c) for c in rest))


def schema_feed(stream: DataFrame, apply: Callable[[list[dict]], None], checkpoint: str) -> StreamingQuery:
    """Runs apply on each micro-batch of schema changes, in order of their column ``seq``. A batch is a few changes, so it is gathered."""

    def batch(df: DataFrame, epoch: int) -> None:
        changes = [r.asDict() for r in df.orderBy("seq").collect()]
        if changes:
            apply(changes)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
