"""Portable bitmap and graymap files (P1, P2, P4, P5) as a Spark data source, and a writer.

``read(spark, path)`` lists files with Spark's own reader, so any store that Spark reads will do; the data source
"netpbm" gives the same rows for local folders, in batch and as a stream of new files."""

from __future__ import annotations

import os
import re

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

PIXELS = "image_id bigint, row int, col int, obj boolean, level int"


def parse(data: bytes) -> np.ndarray:
    """Levels of an image (bitmaps: 1 is object)."""
    kind = data[:2]
    if kind not in (b"P1", b"P2", b"P4", b"P5"):
        raise ValueError("not a portable bitmap or graymap")
    numbers, at = [], 2
    while len(numbers) < (2 if kind in (b"P1", b"P4") else 3):
        m = re.compile(rb"(?:\s|#[^\n]*\n)*(\d+)").match(data, at)
        numbers.append(int(m[1]))
        at = m.end()
    width, height = numbers[:2]
    if kind == b"P1":
        bits = re.sub(rb"#[^\n]*|\s", b"", data[at:])
        return (np.frombuffer(bits, np.uint8)[: width * height] - 48).reshape(height, width).astype(np.int32)
    if kind == b"P2":
        return np.array(re.sub(rb"#[^\n]*", b"", data[at:]).split()[: width * height], np.int32).reshape(height, width)
    body = data[at + 1 :]
    if kind == b"P4":
        row = (width + 7) // 8
        return np.unpackbits(np.frombuffer(body, np.uint8)[: row * height].reshape(height, row), axis=1)[:, :width].astype(np.int32)
    kind_of = np.dtype(">u2") if numbers[2] > 255 else np.dtype(np.uint8)
    return np.frombuffer(body, kind_of)[: width * height].reshape(height, width).astype(np.int32)


def encode(levels: np.ndarray, gray: bool = False) -> bytes:
    """A P4 bitmap (non-zero is object), or a P5 graymap."""
    h, w = levels.shape
    if not gray:
        return b"P4\n%d %d\n" % (w, h) + np.packbits(levels != 0, axis=1).tobytes()
    top = max(int(levels.max(initial=0)), 1)
    return b"P5\n%d %d\n%d\n" % (w, h, top) + levels.astype(">u2" if top > 255 else np.uint8).tobytes()


def _pixels(image: int, data: bytes):
    levels, gray = parse(data), data[:2] in (b"P2", b"P5")
    for r, line in enumerate(levels.tolist()):
        for c, v in enumerate(line):
            yield image, r, c, v > 0, v if gray else None


def read(spark: SparkSession, path: str) -> DataFrame:
    """PIXELS of all images below a path; image_id is a hash of the file's name."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.p[bg]m").option("recursiveFileLookup", "true").load(path)

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            for image, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                levels, gray = parse(data), data[:2] in (b"P2", b"P5")
                r, c = np.indices(levels.shape)
                flat = levels.ravel()
                level = pa.array(flat, pa.int32()) if gray else pa.nulls(len(flat), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(flat), image)), pa.array(r.ravel().astype(np.int32)), pa.array(c.ravel().astype(np.int32)), pa.array(flat > 0), level], ["image_id", "row", "col", "obj", "level"])

    return files.select(F.xxhash64(F.element_at(F.split("path", "/"), -1)).alias("image_id"), "content").mapInArrow(task, PIXELS)


def images(px: DataFrame, gray: bool = False) -> DataFrame:
    """image_id, content: each image of dense pixels as the bytes of a file."""

    def task(table):
        import pyarrow as pa

        rows, cols = table.column("row").to_numpy(), table.column("col").to_numpy()
        array = np.zeros((rows.max() - rows.min() + 1, cols.max() - cols.min() + 1), np.int32)
        array[rows - rows.min(), cols - cols.min()] = table.column("level" if gray else "obj").to_numpy(zero_copy_only=False)
        return pa.table({"image_id": table.column("image_id")[:1], "content": pa.array([encode(array, gray)], pa.binary())})

    return px.groupBy("image_id").applyInArrow(task, "image_id bigint, content binary")


class _Files:
    def __init__(self, options):
        self.folder = options["path"].removeprefix("file://")

    def names(self) -> list[str]:
        return sorted(f for f in os.listdir(self.folder) if f.endswith((".pbm", ".pgm")))

    def rows(self, number: int, name: str):
        with open(os.path.join(self.folder, name), "rb") as file:
            yield from _pixels(number, file.read())


class _Reader(DataSourceReader):
    def __init__(self, files):
        self.files = files

    def partitions(self):
        return [InputPartition((k, n)) for k, n in enumerate(self.files.names())]

    def read(self, partition):
        yield from self.files.rows(*partition.value)


class _StreamReader(SimpleDataSourceStreamReader):
    """New files in the order of their names; the offset is how many were read."""

    def __init__(self, files):
        self.files = files

    def initialOffset(self):
        return {"read": 0}

    def read(self, start):
        names = self.files.names()
        rows = [r for k in range(start["read"], len(names)) for r in self.files.rows(k, names[k])]
        return iter(rows), {"read": len(names)}

    def readBetweenOffsets(self, start, end):
        names = self.files.names()
        return iter([r for k in range(start["read"], end["read"]) for r in self.files.rows(k, names[k])])


class NetpbmSource(DataSource):
    @classmethod
    def name(cls):
        return "netpbm"

    def schema(self):
        return PIXELS

    def reader(self, schema):
        return _Reader(_Files(self.options))

    def simpleStreamReader(self, schema):
        return _StreamReader(_Files(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(NetpbmSource)
