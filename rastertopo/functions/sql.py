"""The SQL surface: views of a raster, and the smoothing filter as a table function."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .kernels import hasf


@udtf(returnType="image_id: bigint, row: int, col: int")
class HomotopicSmooth:
    """TABLE(image_id, row, col, obj, radius) PARTITION BY image_id: the object cells of the smoothed image."""

    def __init__(self):
        self.cells, self.image, self.radius = [], None, 0

    def eval(self, cell):
        self.image, self.radius = cell["image_id"], cell["radius"]
        self.cells.append((cell["row"], cell["col"], cell["obj"]))

    def terminate(self):
        import numpy as np

        if not self.cells:
            return
        rows, cols, obj = (np.array(x) for x in zip(*self.cells))
        margin = 2 * self.radius + 2
        r0, c0 = (int(x.min()) - margin - (int(x.min()) - margin) % 2 for x in (rows, cols))
        image = np.zeros((int(rows.max()) + margin + 1 - r0, int(cols.max()) + margin + 1 - c0), bool)
        image[rows - r0, cols - c0] = obj
        for r, c in np.argwhere(hasf(image, int(self.radius))):
            yield self.image, int(r) + r0, int(c) + c0


def register(spark: SparkSession, px: DataFrame) -> None:
    """Registers the view ``pixels`` and the table function ``homotopic_smooth``."""
    px.createOrReplaceTempView("pixels")
    spark.udtf.register("homotopic_smooth", HomotopicSmooth)
