"""Products over streams: with B fixed, C grows by (new part of A) B, so counts by window can be kept up to date."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.operators.blocks import MatrixFrame


def event_entries(events: DataFrame) -> DataFrame:
    """(ts, row, col, value): user by event type, one a row; ts as a timestamp, which watermarks need."""
    code = F.expr("array_position(array('click', 'error', 'purchase', 'signup', 'view'), event_type)").cast("long")
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("row"), code.alias("col"), F.lit(1).cast("long").alias("value"))


def stream_product(entries: DataFrame, b: MatrixFrame, window: str = "1 day", slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(start, row, col, value): A of each window times B. entries: (ts, row, col, value), a stream or a batch."""
    if watermark:
        entries = entries.withWatermark("ts", watermark)
    right = b.df.select(F.col("row").alias("col"), F.col("col").alias("out"), F.col("value").alias("vb"))
    joined = entries.join(right, "col")
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return joined.groupBy(span.alias("w"), "row", "out").agg(F.sum(F.col("value") * F.col("vb")).alias("value")).select(F.col("w.start").alias("start"), "row", F.col("out").alias("col"), "value")


def session_product(entries: DataFrame, b: MatrixFrame, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    """As stream_product, over the sessions of each row."""
    if watermark:
        entries = entries.withWatermark("ts", watermark)
    right = b.df.select(F.col("row").alias("col"), F.col("col").alias("out"), F.col("value").alias("vb"))
    return entries.join(right, "col").groupBy(F.session_window("ts", gap).alias("w"), "row", "out").agg(F.sum(F.col("value") * F.col("vb")).alias("value")).select(F.col("w.start").alias("start"), "row", F.col("out").alias("col"), "value")


def deduplicated(events: DataFrame, watermark: str = "10 minutes") -> DataFrame:
    """Events once each, by event_id, within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "complete") -> None:
    """Run what is there into a table in memory and wait for it."""
    stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def accumulate(spark: SparkSession, stream: DataFrame, b: MatrixFrame, path: str, checkpoint: str) -> None:
    """C += (new part of A) B by micro-batch: each batch's product is a file set named by the batch, so a batch that runs twice
    overwrites its own and counts once. `product_of` sums them."""
    _by_batch(stream, lambda batch: batch.join(b.df.select(F.col("row").alias("col"), F.col("col").alias("out"), F.col("value").alias("vb")), "col").groupBy("row", "out").agg(F.sum(F.col("value") * F.col("vb")).alias("value")).select("row", F.col("out").alias("col"), "value"), path, checkpoint)


def accumulate_windows(stream: DataFrame, b: MatrixFrame, path: str, checkpoint: str, window: str = "1 day", slide: str | None = None) -> None:
    """As accumulate, for the products of each window; `window_product_of` sums them. No sum is kept between batches, so neither an
    executor's state nor the driver's memory bounds how many windows and rows there are."""
    _by_batch(stream, lambda batch: stream_product(batch, b, window, slide), path, checkpoint)


def _by_batch(stream: DataFrame, product: Callable[[DataFrame], DataFrame], path: str, checkpoint: str) -> None:
    def fold(batch: DataFrame, number: int) -> None:
        product(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.foreachBatch(fold).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def product_of(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).groupBy("row", "col").agg(F.sum("value").alias("value"))


def window_product_of(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("start timestamp, row long, col long, value long").parquet(path).groupBy("start", "row", "col").agg(F.sum("value").alias("value"))


def change_of_both(a: MatrixFrame, b: MatrixFrame, da: MatrixFrame, db: MatrixFrame) -> MatrixFrame:
    """What the product gains when both operands change: dA B + A dB + dA dB."""
    from gridmul.operators.multiply import relational_multiply

    return relational_multiply(da, b).add(relational_multiply(a, db)).add(relational_multiply(da, db))
