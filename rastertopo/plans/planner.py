"""Chooses the physical form of distances and filters from the sizes of the images, before any DataFrame is built."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import distance as D
from ..operators import homotopic as H
from ..operators.layout import frames


@dataclass(frozen=True)
class Sizes:
    images: int
    largest: int
    rows: int


def sizes(px: DataFrame) -> Sizes:
    """Number of images, cells of the largest frame and its rows: one aggregate, three numbers to the driver."""
    box = frames(px).agg(F.count(F.lit(1)).alias("n"), F.max(F.col("n_rows").cast("long") * F.col("n_cols")).alias("cells"), F.max("n_rows").alias("rows")).first()
    return Sizes(box.n, box.cells or 0, box.rows or 0)


def distance_plan(size: Sizes, radius: int | None = None) -> str:
    """capped: only a threshold is needed, so expressions within the radius; image: frames fit a task; tiled otherwise."""
    if radius is not None and (size.largest > H.IMAGE_PIXELS or radius <= 5):
        return "capped"
    return "image" if size.largest <= H.IMAGE_PIXELS else "tiled"


def distance(px: DataFrame, target: str = "object", radius: int | None = None, size: Sizes | None = None) -> DataFrame:
    plan = distance_plan(size or sizes(px), radius)
    if plan == "capped":
        return D.edt_capped(px, radius, target)
    return D.edt_image(px, target) if plan == "image" else D.edt_tiled(px, 1024, target)


def filter_steps(n: int) -> list[tuple[str, int]]:
    """The primitive steps of the smoothing filter of radius n, in order; one distance serves a threshold and an order."""
    steps = []
    for r in range(1, n + 1):
        steps += [("thin to erosion", r), ("thicken in dilation", r), ("thicken to dilation", r), ("thin to erosion or image", r)]
    return steps


def thin(px: DataFrame, keep: DataFrame | None = None, conn: str = "8/4", size: Sizes | None = None) -> DataFrame:
    """Image strategy while the largest frame fits a task, else super-steps over tiles."""
    small = (size or sizes(px)).largest <= H.IMAGE_PIXELS
    return H.thin(px, keep, conn) if small else H.thin_tiles(px, keep, conn)
