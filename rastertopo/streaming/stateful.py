"""Event-based coordination of tiles and workers: state by key, late events, finish times, static control images."""

from __future__ import annotations

import json
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import kernels as K
from ..plans.lineage import folder

TILE_OUT = "image_id long, tile_r int, tile_c int, version int, n_before long, n_after long"
TILE_STATE = "bits binary, version int"
MERGE_OUT = "image_id long, round int, child int, p1 long, p2 long"
MERGE_STATE = "waiting string, made string"


def tile_filter(pixels: DataFrame, side: int, radius: int, conn: str = "8/4") -> DataFrame:
    """Pixels (image_id, row, col, obj) into tiles of ``side`` x ``side`` cells, smoothed as their pixels come.

    The state of a tile is its cells, packed. Each batch sets cells and smooths the tile anew with its border ring kept,
    so neighbouring tiles still fit; a row tells the tile's version and its cells before and after. Late cells of a tile
    raise its version, nothing is thrown away."""

    def update(key, frames, state: GroupState):
        image, tile_r, tile_c = key
        bits, version = state.get if state.exists else (b"", 0)
        x = np.unpackbits(np.frombuffer(bits, np.uint8))[: side * side].reshape(side, side).astype(bool) if bits else np.zeros((side, side), bool)
        for f in frames:
            x[f["row"].to_numpy() - tile_r * side, f["col"].to_numpy() - tile_c * side] = f["obj"].to_numpy()
        state.update((np.packbits(x).tobytes(), version + 1))
        ring = np.ones((side, side), bool)
        ring[1:-1, 1:-1] = False
        y = K.hasf(x, radius, x & ring, ~x & ring, conn)
        yield pd.DataFrame({"image_id": [image], "tile_r": [tile_r], "tile_c": [tile_c], "version": [version + 1], "n_before": [int(x.sum())], "n_after": [int(y.sum())]})

    at = pixels.select("image_id", "row", "col", "obj", F.floor(F.col("row") / side).cast("int").alias("tile_r"), F.floor(F.col("col") / side).cast("int").alias("tile_c"))
    return at.groupBy("image_id", "tile_r", "tile_c").applyInPandasWithState(update, TILE_OUT, TILE_STATE, "update", GroupStateTimeout.NoTimeout)


def finish_merge(finished: DataFrame) -> DataFrame:
    """Workers (image_id, worker_id, finish) that pair up as their events come: image_id, round, child, p1, p2.

    Workers of a batch come in the order of their finish. A finished worker waits until another of its round is there;
    their child enters the next round at once."""

    def update(key, frames, state: GroupState):
        waiting, made = (json.loads(x) for x in state.get) if state.exists else ({}, {})
        come = pd.concat(list(frames)).sort_values(["finish", "worker_id"])
        out = []
        for worker in come["worker_id"].tolist():
            level, node = 1, int(worker)
            while (other := waiting.pop(str(level), None)) is not None:
                child = made.get(str(level), 0)
                made[str(level)] = child + 1
                out.append((key[0], level, child, other, node))
                level, node = level + 1, child
            waiting[str(level)] = node
        state.update((json.dumps(waiting), json.dumps(made)))
        yield pd.DataFrame(out, columns=["image_id", "round", "child", "p1", "p2"])

    return finished.groupBy("image_id").applyInPandasWithState(update, MERGE_OUT, MERGE_STATE, "append", GroupStateTimeout.NoTimeout)


def left_alone(pairs: DataFrame, workers: DataFrame) -> DataFrame:
    """What the pairs of ``finish_merge`` lack once all workers (image_id, worker_id) are known: of an odd number the one that
    no other met goes on alone (p2 null) as the last child of round 1, and pairs with those that wait in later rounds."""
    first = pairs.filter("round = 1")
    met = first.select("image_id", F.explode(F.array("p1", "p2")).alias("worker_id"))
    alone = workers.select("image_id", "worker_id").join(met, ["image_id", "worker_id"], "left_anti")
    made = first.groupBy("image_id").agg(F.count(F.lit(1)).alias("n"))
    last = alone.join(made, "image_id", "left").select("image_id", F.col("worker_id").cast("long").alias("node"), F.coalesce("n", F.lit(0).cast("long")).alias("n"))
    # In round k + 2 the child n >> k meets the one before it as long as the last bits of n are set.
    later = F.expr("filter(sequence(0, 60), k -> pmod(n + 1, shiftleft(2L, k)) = 0)")
    own = last.select("image_id", F.lit(1).alias("round"), F.col("n").cast("int").alias("child"), F.col("node").alias("p1"), F.lit(None).cast("long").alias("p2"))
    met_later = last.select("image_id", "n", F.explode(later).alias("k")).withColumn("p2", F.expr("shiftright(n, k)"))
    return own.unionByName(met_later.select("image_id", (F.col("k") + 2).cast("int").alias("round"), F.expr("shiftright(p2, 1)").cast("int").alias("child"), (F.col("p2") - 1).alias("p1"), "p2"))


def late_cells(events: DataFrame) -> DataFrame:
    """Cells a day of a stream with a watermark on ts, in append mode: a day's image comes when the watermark has passed it, and later events are dropped."""
    day = F.window("ts", "1 day").alias("w")
    cell = [F.pmod("user_id", F.lit(168)).cast("int").alias("row"), F.expr("(hour(ts) * 60 + minute(ts)) div 5").cast("int").alias("col")]
    counts = events.groupBy(day, *cell).agg(F.count(F.lit(1)).alias("n"))
    return counts.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "row", "col", "n")


def controlled(events: DataFrame, control: DataFrame) -> DataFrame:
    """Cells of a stream that lie on a static control image (row, col): counts by event type."""
    cell = events.select("event_type", F.pmod("user_id", F.lit(168)).cast("int").alias("row"), F.expr("(hour(ts) * 60 + minute(ts)) div 5").cast("int").alias("col"))
    return cell.join(control.select("row", "col").distinct(), ["row", "col"]).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def rows_of(spark: SparkSession, streamed: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all there is and returns the rows that it gave, from a table in the shared folder.

    In complete mode each batch gives all rows anew, so only the last one's stay."""
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/batch={0 if mode == 'complete' else number}")

    streamed.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(streamed.schema).parquet(f"{base}/rows/batch=*")
