"""Windows and sketches over event streams.  The same functions serve batch tables and
streams; on a stream set a watermark first (``timed`` does so for its delay)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.sketch import BlockSketch

SKETCH = BlockSketch(3, 1, 8, 2)


def timed(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    out = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return out.withWatermark("ts", delay) if events.isStreaming else out


def _sums(grouped) -> DataFrame:
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("v"))


def tumbling(events: DataFrame, span: str = "1 day") -> DataFrame:
    return _sums(events.groupBy(F.window("ts", span)))


def sliding(events: DataFrame, span: str = "7 days", step: str = "1 day") -> DataFrame:
    return _sums(events.groupBy(F.window("ts", span, step)))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return _sums(events.groupBy(F.session_window("ts", gap), "user_id"))


def dedup(events: DataFrame) -> DataFrame:
    """Each event once; a sketch that counts a row twice would be biased."""
    return events.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def sketch_by_window(events: DataFrame, span: str = "1 day", sketch: BlockSketch = SKETCH) -> DataFrame:
    """(window, block, bucket, v): the sketch of the values of each window."""
    placed = sketch.placed(events.withColumnRenamed("event_id", "row_id"))
    return placed.groupBy(F.window("ts", span), "block", "bucket").agg(F.sum(F.col("sign") * F.col("value")).alias("v"))


def without(total: DataFrame, expired: DataFrame) -> DataFrame:
    """Sketch entries of ``total`` less those of ``expired`` (sliding out old windows)."""
    keys = ["block", "bucket"]
    signed = total.select(*keys, "v").unionByName(expired.select(*keys, (-F.col("v")).alias("v")))
    return signed.groupBy(*keys).agg(F.sum("v").alias("v"))


def late_mass(events: DataFrame, delay: str = "1 hour", arrival: str = "arrived") -> DataFrame:
    """(window, n, late, late_v) by day: events, and the number and absolute value of those
    that came after the watermark had passed their window's end, which a stream drops.
    ``arrival``: when an event came."""
    day = F.window("ts", "1 day")
    late = F.col(arrival).cast("timestamp") > day["end"] + F.expr(f"INTERVAL {delay}")
    rows = events.withColumn("_late", late)
    return rows.groupBy(day).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("_late").cast("int")).alias("late"), F.sum(F.when(F.col("_late"), F.abs("value")).otherwise(0.0)).alias("late_v"))


def with_static(events: DataFrame, table: DataFrame, key: str, other: str) -> DataFrame:
    """Stream (or batch) events with the columns of a static table, whose size Spark checks
    before it broadcasts; events without a match stay."""
    return events.join(table, events[key] == table[other], "left")


def run_available(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Process what is there, into Parquet files, and stop."""
    df.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path).awaitTermination()


def warm_newton(stream: DataFrame, step, state: dict, checkpoint: str) -> None:
    """A Newton step on every micro-batch, from where the last one ended: ``step(batch, w)``
    gives the next weights, kept in ``state['w']``."""

    def each(batch: DataFrame, _: int) -> None:
        if not batch.isEmpty():
            state["w"] = step(batch, state.get("w"))

    stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
