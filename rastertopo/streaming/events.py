"""Streams of pixels from events: daily images, sliding densities, sessions, and smoothing by micro-batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import homotopic as H


def stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a file stream with a watermark of ten minutes."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "10 minutes")


def day_cells(events: DataFrame) -> DataFrame:
    """One image a day: the cells with their counts."""
    day = F.window("ts", "1 day").alias("w")
    cell = [F.pmod("user_id", F.lit(168)).cast("int").alias("row"), F.expr("(hour(ts) * 60 + minute(ts)) div 5").cast("int").alias("col")]
    counts = events.groupBy(day, *cell).agg(F.count(F.lit(1)).alias("n"))
    return counts.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "row", "col", "n")


def sliding_cells(events: DataFrame) -> DataFrame:
    """Densities of the last day, each hour."""
    counts = events.groupBy(F.window("ts", "1 day", "1 hour").alias("w"), F.pmod("user_id", F.lit(168)).cast("int").alias("row")).agg(F.count(F.lit(1)).alias("n"))
    return counts.select(F.col("w.start").alias("start"), "row", "n")


def sessions(events: DataFrame) -> DataFrame:
    """Objects by user: events less than half an hour apart."""
    found = events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return found.select("user_id", F.unix_micros("w.start").alias("started"), "n")


def distinct_pushes(pushes: DataFrame) -> DataFrame:
    """Neighbours to recheck (image_id, row, col, ts), each once within the watermark."""
    return pushes.dropDuplicatesWithinWatermark(["image_id", "row", "col"])


def rechecks(requests: DataFrame, updates: DataFrame) -> DataFrame:
    """Requests (image_id, tile, ts) met by updates of the tile within five minutes after: a stream-stream interval join."""
    u = updates.select(F.col("image_id").alias("_i"), F.col("tile").alias("_t"), F.col("ts").alias("updated"), *[c for c in updates.columns if c not in ("image_id", "tile", "ts")])
    return requests.join(u, F.expr("image_id = _i AND tile = _t AND updated BETWEEN ts AND ts + INTERVAL 5 MINUTES")).drop("_i", "_t")


def smooth_batches(pixels: DataFrame, radius: int, sink: str, checkpoint: str):
    """Smooths the images of each micro-batch as a whole and appends their cells to Parquet. Returns the query."""

    def write(batch: DataFrame, number: int) -> None:
        done = H.hasf(batch.select("image_id", "row", "col", "obj"), radius)
        done.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return pixels.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def replay(spark: SparkSession, sf_dir: str, operator, columns: list[str]) -> DataFrame:
    """Runs a streaming operator over all events there are and returns its final rows (complete output to the shared folder)."""
    from .stateful import rows_of

    return rows_of(spark, operator(stream(spark, sf_dir)), "complete").select(*columns)
