"""Cell tables of event streams: windows, merges and late rows.

The origin is absolute, as the box of a stream is never known; coordinates are
scaled by fixed steps instead, shifted by an even number of units so that cells keep
their parity and stay above zero.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cloudlattice.functions import quantize
from cloudlattice.operators import cells as tables

SHIFT = 1 << 10


def event_cells(events: DataFrame, steps: tuple[float, float, float]) -> DataFrame:
    """Add i, j, k to events (ts, user_id, value): seconds of the day, user and value in units of the steps."""
    second = F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")
    at = [second.cast("double") / F.lit(steps[0]), F.col("user_id").cast("double") / F.lit(steps[1]), F.col("value") / F.lit(steps[2])]
    cell = quantize.bcc_cell([F.col(c) for c in "uvw"])
    return events.withColumns(dict(zip("uvw", at, strict=True))).withColumns({n: c + SHIFT for n, c in zip(quantize.CELL, cell, strict=True)}).drop("u", "v", "w")


def windowed_counts(events: DataFrame, steps: tuple[float, float, float], window: Column, late: str = "1 hour") -> DataFrame:
    """Cells by time window; rows later than the watermark are dropped when the input is a stream."""
    at = event_cells(events, steps).withColumn("ts", F.col("ts").cast("timestamp"))
    if at.isStreaming:
        at = at.withWatermark("ts", late)
    return at.groupBy(window.alias("window"), *quantize.CELL).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), *quantize.CELL, "n")


def kind_counts(events: DataFrame, window: Column, late: str = "1 hour") -> DataFrame:
    """Events by window, tumbling or sliding, and kind."""
    at = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if at.isStreaming:
        at = at.withWatermark("ts", late)
    return at.groupBy(window.alias("window"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: int, late: str = "1 hour") -> DataFrame:
    """Events by user in sessions that end after ``gap`` quiet seconds."""
    at = events.withColumn("ts", F.col("ts").cast("timestamp"))
    if at.isStreaming:
        at = at.withWatermark("ts", late)
    return at.groupBy("user_id", F.session_window("ts", f"{gap} seconds").alias("window")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("window.start").alias("start"), "n")


ALERT = "user_id long, seen long, crossed timestamp"


def alerts(events: DataFrame, least: int) -> DataFrame:
    """user_id, seen, crossed: users whose events reach ``least``, once each, with the time of the event that did it.

    On a stream the count of each user is kept as state; rows that repeat a time count each.
    """
    import pandas as pd

    at = events.select(F.col("user_id").cast("long").alias("user_id"), F.col("ts").cast("timestamp").alias("ts"))

    def step(key, batches, state):
        seen = state.get[0] if state.exists else 0
        times = sorted(t for batch in batches for t in batch["ts"])
        if seen < least <= seen + len(times):
            yield pd.DataFrame({"user_id": [key[0]], "seen": [least], "crossed": [times[least - seen - 1]]})
        state.update((seen + len(times),))

    if at.isStreaming:
        return at.groupBy("user_id").applyInPandasWithState(step, ALERT, "seen long", "append", "NoTimeout")
    order = Window.partitionBy("user_id").orderBy("ts")
    return at.withColumn("seen", F.row_number().over(order).cast("long")).where(F.col("seen") == least).select("user_id", "seen", F.col("ts").alias("crossed"))


def merge_batches(stream: DataFrame, path: str, checkpoint: str):
    """Start a query that adds each batch's cell table to a folder, one file set a batch; a batch that is run again replaces itself."""

    def add(batch: DataFrame, epoch: int) -> None:
        tables.run_lengths(batch.select(*quantize.CELL)).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def merged_table(spark: SparkSession, path: str) -> DataFrame:
    """The cell table of all batches so far: merging is associative."""
    return tables.run_lengths(spark.read.parquet(path).select(*quantize.CELL, "n"))
