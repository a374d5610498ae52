"""What the corpus operators share: reading, scratch tables and a fixed-size key filter."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bits of one bitmap of ``bitmap_construct_agg``.
BITMAP_BITS = 32768


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: the cluster's checkpoint folder.

    Only where none is set (a local session of the tests) a temporary folder of this machine is taken."""
    conf = spark.sparkContext.getConf()
    path = conf.get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not path:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        path = tempfile.mkdtemp(prefix="corpus-scratch-")
        spark.sparkContext.setCheckpointDir(path)
    return path


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str, **options: str) -> DataFrame:
    """``df`` written as Parquet to the shared folder and read again: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


class KeyFilter:
    """A one-hash Bloom filter of fixed size over a key column, in JVM expressions only.

    ``bits`` bounds what is broadcast (bits / 8 bytes) whatever the number of keys. A saturated filter passes
    rows that a later join or aggregate removes; it never loses one."""

    def __init__(self, keys: DataFrame, column: str, bits: int = 1 << 23):
        self.bits = bits
        place = self._place(F.col(column))
        self.maps = keys.groupBy((place / BITMAP_BITS).cast("long").alias("_map")).agg(
            F.bitmap_construct_agg(F.pmod(place, F.lit(BITMAP_BITS))).alias("_bits")
        )

    def _place(self, key: Column) -> Column:
        return F.pmod(F.xxhash64(key), F.lit(self.bits))

    def prune(self, rows: DataFrame, key: str) -> DataFrame:
        """The rows whose key may be among the filter's keys."""
        return self.flag(rows, key, "_hit").filter("_hit").drop("_hit")

    def flag(self, rows: DataFrame, key: str, column: str) -> DataFrame:
        """Adds ``column``: whether the key may be among the filter's keys."""
        place = self._place(F.col(key))
        bit = F.pmod(place, F.lit(BITMAP_BITS))
        byte = F.conv(F.hex(F.substr(F.col("_bits"), (bit / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
        hit = F.coalesce(F.expr("shiftright(_byte, cast(pmod(_bit, 8) as int)) & 1") == 1, F.lit(False))
        return (
            rows.withColumn("_map", (place / BITMAP_BITS).cast("long"))
            .join(F.broadcast(self.maps), "_map", "left")
            .withColumn("_bit", bit)
            .withColumn("_byte", byte)
            .withColumn(column, hit)
            .drop("_map", "_bits", "_bit", "_byte")
        )


#: Rows that a Python task holds as Python objects at once.
SLICE_ROWS = 256


def slices(batches):
    """Arrow batches cut small, so that few texts are Python objects at a time."""
    import pyarrow as pa

    for batch in batches:
        for start in range(0, batch.num_rows, SLICE_ROWS):
            yield batch.slice(start, SLICE_ROWS)
    released()


def released() -> None:
    """Workers stay for later tasks; what this one took and no longer holds goes back to the system."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def worker_state() -> dict:
    """What a Python worker keeps from task to task (caches only; a new worker starts empty)."""
    import sys
    import types

    return sys.modules.setdefault("_corpus_worker_state", types.ModuleType("_corpus_worker_state")).__dict__
