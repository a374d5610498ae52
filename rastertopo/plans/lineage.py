"""Cutting the lineage of iterations so that it survives lost executors."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def folder(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints, which the driver and all executors see.

    Only a local session without such a folder takes a temporary one."""
    path = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not path:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        path = tempfile.mkdtemp(prefix="raster-checkpoints-")
        spark.sparkContext.setCheckpointDir(path)
    return path.rstrip("/")


def saved(df: DataFrame) -> DataFrame:
    """``df`` written as Parquet to the shared folder, and read again.

    A file has a size; the estimate of a checkpointed plan would grow with each join of a loop."""
    spark = df.sparkSession
    path = f"{folder(spark)}/raster-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
