"""Disc morphology by thresholds of capped distances, and the smoothing baselines without regard to topology."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from .blocks import transform
from .distance import edt_capped
from .layout import KEY
from .topology import ball


def dilate(px: DataFrame, r: int) -> DataFrame:
    """Object cells of the dilation within the frame of the pixels."""
    return edt_capped(px, r, "object").filter("d2 IS NOT NULL").select(*KEY)


def erode(px: DataFrame, r: int) -> DataFrame:
    """Object cells farther than r from the background of the frame."""
    return edt_capped(px, r, "background").filter("d2 IS NULL").select(*KEY)


def mark(px: DataFrame, pt: DataFrame) -> DataFrame:
    """Pixels of the frame of ``px`` with obj: whether the cell is in ``pt``."""
    return px.select(*KEY).join(pt.select(*KEY, F.lit(True).alias("obj")), KEY, "left").withColumn("obj", F.coalesce("obj", F.lit(False)))


def opening(px: DataFrame, r: int) -> DataFrame:
    return dilate(mark(px, erode(px, r)), r)


def closing(px: DataFrame, r: int) -> DataFrame:
    return erode(mark(px, dilate(px, r)), r)


def asf(px: DataFrame, n: int) -> DataFrame:
    """The plain alternating sequential filter: opening, then closing, of radius 1 to n."""
    pt = None
    for r in range(1, n + 1):
        pt = opening(px, r)
        px = mark(px, pt)
        pt = closing(px, r)
        px = mark(px, pt)
    return pt


def dilate_scatter(pt: DataFrame, r: int) -> DataFrame:
    """The definition: every object cell scatters the ball (a table of fixed size)."""
    spread = pt.select(*KEY).crossJoin(F.broadcast(ball(pt.sparkSession, r)))
    return spread.select("image_id", (F.col("row") + F.col("dr")).alias("row"), (F.col("col") + F.col("dc")).alias("col")).distinct()


def square_dilate(px: DataFrame, r: int) -> DataFrame:
    """A square instead of a ball: running maxima along rows, then columns."""
    across = Window.partitionBy("image_id", "row").orderBy("col").rowsBetween(-r, r)
    down = Window.partitionBy("image_id", "col").orderBy("row").rowsBetween(-r, r)
    return px.select(*KEY, F.max("obj").over(across).alias("obj")).select(*KEY, F.max("obj").over(down).alias("obj")).filter("obj").select(*KEY)


def square_erode(px: DataFrame, r: int) -> DataFrame:
    across = Window.partitionBy("image_id", "row").orderBy("col").rowsBetween(-r, r)
    down = Window.partitionBy("image_id", "col").orderBy("row").rowsBetween(-r, r)
    return px.select(*KEY, F.min("obj").over(across).alias("obj")).select(*KEY, F.min("obj").over(down).alias("obj")).filter("obj").select(*KEY)


def asf_image(px: DataFrame, n: int) -> DataFrame:
    """The plain filter with one image in a task."""
    return transform(px, lambda x: K.asf(x, n), margin=n + 1)


def laplacian_smooth(curve: DataFrame, lam: float, rounds: int = 1) -> DataFrame:
    """Points (curve_id, pos, x, y) moved towards the mean of their neighbours on the curve; ends stay."""
    order = Window.partitionBy("curve_id").orderBy("pos")
    for _ in range(rounds):
        near = curve.withColumns({f"{k}{v}": f(v).over(order) for k, f in (("p", F.lag), ("n", F.lead)) for v in ("x", "y")})
        move = lambda v: F.when(F.col(f"p{v}").isNull() | F.col(f"n{v}").isNull(), F.col(v)).otherwise(F.col(v) + lam * ((F.col(f"p{v}") + F.col(f"n{v}")) / 2 - F.col(v)))
        curve = near.select("curve_id", "pos", move("x").alias("x"), move("y").alias("y"))
    return curve


def curvature(curve: DataFrame) -> DataFrame:
    """Adds ``turn``: the angle between successive steps of a curve; null at its ends."""
    order = Window.partitionBy("curve_id").orderBy("pos")
    near = curve.withColumns({f"{k}{v}": f(v).over(order) for k, f in (("p", F.lag), ("n", F.lead)) for v in ("x", "y")})
    ax, ay, bx, by = F.col("x") - F.col("px"), F.col("y") - F.col("py"), F.col("nx") - F.col("x"), F.col("ny") - F.col("y")
    return near.select("curve_id", "pos", "x", "y", F.atan2(ax * by - ay * bx, ax * bx + ay * by).alias("turn"))


def curvature_filter(curve: DataFrame, k: int) -> DataFrame:
    """The curvature plot opened by a segment of 2 k + 1 points: running minimum, then running maximum."""
    near = Window.partitionBy("curve_id").orderBy("pos").rowsBetween(-k, k)
    low = curvature(curve).withColumn("low", F.min("turn").over(near))
    return low.select("curve_id", "pos", "turn", F.max("low").over(near).alias("opened"))


def residues(before: DataFrame, after: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Salient cells (gone by smoothing) and carved ones (added by it)."""
    a, b = before.select(*KEY), after.select(*KEY)
    return a.join(b, KEY, "left_anti"), b.join(a, KEY, "left_anti")


def area_by_radius(px: DataFrame, radii: list[int]) -> DataFrame:
    """image_id, r, area, lost: the area of the opening by each radius, and what the step from the former radius took."""
    found = px.filter("obj").groupBy("image_id").agg(F.count(F.lit(1)).alias("area")).withColumn("r", F.lit(0))
    for r in radii:
        found = found.unionByName(opening(px, r).groupBy("image_id").agg(F.count(F.lit(1)).alias("area")).withColumn("r", F.lit(r)))
    order = Window.partitionBy("image_id").orderBy("r")
    return found.select("image_id", "r", "area", (F.lag("area").over(order) - F.col("area")).alias("lost"))
