"""Distance transforms: the exact two-pass transform in several physical forms, and the approximate ones it replaces.

Squared integer distances; null means that the image has no feature (or none within the cap)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from .blocks import cell_table, per_image, raster
from .layout import KEY

DIST = "image_id long, row int, col int, d2 long"


def features(px: DataFrame, target: str = "object") -> DataFrame:
    """Pixels with ``feature``: the object, or the background, is what distances lead to."""
    return px.select(*KEY, (F.col("obj") if target == "object" else ~F.col("obj")).alias("feature"))


def vertical_gap(px: DataFrame, target: str = "object") -> DataFrame:
    """Pass 1: adds g, the vertical distance to the nearest feature of the column (as-of lookups up and down; one sort)."""
    down = Window.partitionBy("image_id", "col").orderBy("row")
    at = F.when(F.col("feature"), F.col("row"))
    above = F.last(at, ignorenulls=True).over(down.rowsBetween(Window.unboundedPreceding, 0))
    below = F.first(at, ignorenulls=True).over(down.rowsBetween(0, Window.unboundedFollowing))
    seen = features(px, target).withColumns({"_a": above, "_b": below})
    return seen.select(*KEY, "feature", F.least(F.col("row") - F.col("_a"), F.col("_b") - F.col("row")).alias("g"))


def edt_exact(px: DataFrame, target: str = "object") -> DataFrame:
    """Two passes over dense pixels: columns by window, rows by the lower envelope of parabolas in one Arrow call a row."""

    def row(table):
        import pyarrow as pa

        table = table.sort_by("col")
        gaps = table.column("g").to_numpy(zero_copy_only=False)
        gaps = np.where(np.isnan(gaps.astype(float)), K.FAR, np.nan_to_num(gaps.astype(float))).astype(np.int64)
        d = K.lower_envelope(gaps)
        return pa.table([table.column("image_id"), table.column("row"), table.column("col"), pa.array(d, mask=d >= K.FAR)], names=["image_id", "row", "col", "d2"])

    return vertical_gap(px, target).select(*KEY, "g").groupBy("image_id", "row").applyInArrow(row, DIST)


def edt_rows(px: DataFrame, target: str = "object") -> DataFrame:
    """Pass 2 in expressions only: for each place of a row the least of g squared plus the column offset squared."""
    rows = vertical_gap(px, target).groupBy("image_id", "row").agg(F.array_sort(F.collect_list(F.struct("col", "g"))).alias("line"))
    best = lambda p: F.array_min(F.transform("line", lambda c: c["g"].cast("long") * c["g"] + (p["col"] - c["col"]).cast("long") * (p["col"] - c["col"])))
    done = rows.select("image_id", "row", F.explode(F.transform("line", lambda p: F.struct(p["col"].alias("col"), best(p).alias("d2")))).alias("x"))
    return done.select("image_id", "row", "x.col", "x.d2")


def edt_image(px: DataFrame, target: str = "object", method: str = "exact", radius: int | None = None, first: str = "columns") -> DataFrame:
    """One image in a task: methods exact, capped, scan4, scan3x3, prop4, prop8, prop_exact; ``first``: the axis of the first pass."""

    def task(table):
        image, r0, c0, a = raster(table, 0, {"f": ("feature", bool, False), "in": (None, bool, False)})
        f = a["f"] if first == "columns" else a["f"].T
        d = METHODS[method](f) if method != "capped" else K.capped_distance(f, radius)
        d = d if first == "columns" else d.T
        out = cell_table(image, r0, c0, a["in"], {"d2": d})
        import pyarrow as pa

        values = out.column("d2").to_numpy()
        return out.set_column(3, "d2", pa.array(values, pa.int64(), mask=values >= K.FAR))

    return per_image(features(px, target), task, DIST)


METHODS = {
    "exact": K.distance,
    "scan4": K.scan4_distance,
    "scan3x3": K.scan3x3_distance,
    "prop4": lambda f: K.propagated_distance(f, 4),
    "prop8": lambda f: K.propagated_distance(f, 8),
    "prop_exact": lambda f: K.propagated_distance(f, 8, exact=True),
}


def edt_capped(px: DataFrame, radius: int, target: str = "object") -> DataFrame:
    """Exact up to ``radius``, null beyond, in expressions: gaps within reach scatter over 2 radius + 1 columns, least wins before the shuffle."""
    near = vertical_gap(px, target).filter(F.col("g") <= radius).select("image_id", "row", "col", "g")
    sent = near.select("image_id", "row", F.explode(F.sequence(F.lit(-radius), F.lit(radius))).alias("dc"), "col", "g")
    sent = sent.select("image_id", "row", (F.col("col") + F.col("dc")).alias("col"), (F.col("g") * F.col("g") + F.col("dc") * F.col("dc")).cast("long").alias("d2")).filter(F.col("d2") <= radius * radius)
    own = px.select(*KEY, F.lit(None).cast("long").alias("d2"), F.lit(True).alias("here"))
    met = own.unionByName(sent.withColumn("here", F.lit(False))).groupBy(*KEY).agg(F.min("d2").alias("d2"), F.max("here").alias("here"))
    return met.filter("here").drop("here")


def edt_parallel(px: DataFrame, workers: int, target: str = "object") -> DataFrame:
    """Columns, then rows, dealt in strides to workers; the shuffle between the passes is the only meeting point."""

    def columns(key, table):
        import pyarrow as pa

        image, r0, c0, a = raster(table, 0, {"f": ("feature", bool, False), "in": (None, bool, False)})
        out = cell_table(image, r0, c0, a["in"], {"g": K.column_gaps(a["f"])})
        values = out.column("g").to_numpy()
        return out.set_column(3, "g", pa.array(values, pa.int64(), mask=values >= K.FAR))

    def rows(key, table):
        import pyarrow as pa

        image, r0, c0, a = raster(table, 0, {"in": (None, bool, False)})
        gaps = np.full(a["in"].shape, K.FAR)
        g = table.column("g").to_numpy(zero_copy_only=False).astype(float)
        gaps[table.column("row").to_numpy() - r0, table.column("col").to_numpy() - c0] = np.where(np.isnan(g), K.FAR, np.nan_to_num(g)).astype(np.int64)
        d = np.stack([K.lower_envelope(x) for x in gaps])
        out = cell_table(image, r0, c0, a["in"], {"d2": d})
        values = out.column("d2").to_numpy()
        return out.set_column(3, "d2", pa.array(values, pa.int64(), mask=values >= K.FAR))

    first = features(px, target).groupBy("image_id", F.pmod("col", F.lit(workers)).alias("w")).applyInArrow(columns, "image_id long, row int, col int, g long")
    return first.groupBy("image_id", F.pmod("row", F.lit(workers)).alias("w")).applyInArrow(rows, DIST)


def edt_tiled(px: DataFrame, side: int, target: str = "object") -> DataFrame:
    """The first pass by tiles: each tile scans its columns, and only the last and first feature of each column move on.

    What moves between tiles is a row for each tile and column, not the pixels: two per column of a tile."""
    at = features(px, target).withColumn("tile", F.floor(F.col("row") / side).cast("int"))
    mark = F.when(F.col("feature"), F.col("row"))
    carry = at.groupBy("image_id", "col", "tile").agg(F.max(mark).alias("last"), F.min(mark).alias("first"))
    order = Window.partitionBy("image_id", "col").orderBy("tile")
    carry = carry.select("image_id", "col", "tile", F.last("last", True).over(order.rowsBetween(Window.unboundedPreceding, -1)).alias("above"), F.first("first", True).over(order.rowsBetween(1, Window.unboundedFollowing)).alias("below"))
    inside = Window.partitionBy("image_id", "tile", "col").orderBy("row")
    own = at.withColumns({"_a": F.last(mark, True).over(inside.rowsBetween(Window.unboundedPreceding, 0)), "_b": F.first(mark, True).over(inside.rowsBetween(0, Window.unboundedFollowing))})
    met = own.join(carry, ["image_id", "tile", "col"])
    gap = F.least(F.col("row") - F.coalesce("_a", "above"), F.coalesce("_b", "below") - F.col("row"))
    gaps = met.select(*KEY, gap.alias("g"))
    rows = gaps.groupBy("image_id", "row").agg(F.array_sort(F.collect_list(F.struct("col", "g"))).alias("line"))
    best = lambda p: F.array_min(F.transform("line", lambda c: c["g"].cast("long") * c["g"] + (p["col"] - c["col"]).cast("long") * (p["col"] - c["col"])))
    done = rows.select("image_id", "row", F.explode(F.transform("line", lambda p: F.struct(p["col"].alias("col"), best(p).alias("d2")))).alias("x"))
    return done.select("image_id", "row", "x.col", "x.d2")


def edt_3d(pt: DataFrame, depth: list[str]) -> DataFrame:
    """Three axes (z, row, col) of dense voxels with ``obj``: each axis takes the least of the former plus the offset squared."""
    down = Window.partitionBy("z", "col").orderBy("row")
    at = F.when(F.col("obj"), F.col("row"))
    above, below = F.last(at, True).over(down.rowsBetween(Window.unboundedPreceding, 0)), F.first(at, True).over(down.rowsBetween(0, Window.unboundedFollowing))
    d = pt.withColumns({"_a": above, "_b": below}).withColumn("g", F.least(F.col("row") - F.col("_a"), F.col("_b") - F.col("row")))
    d = d.select(*depth, (F.col("g") * F.col("g")).cast("long").alias("d2"))
    for axis, others in (("col", ["z", "row"]), ("z", ["row", "col"])):
        line = d.groupBy(*others).agg(F.collect_list(F.struct(F.col(axis).alias("p"), "d2")).alias("line"))
        best = lambda q: F.array_min(F.transform("line", lambda c: c["d2"] + ((q["p"] - c["p"]) * (q["p"] - c["p"])).cast("long")))
        d = line.select(*others, F.explode(F.transform("line", lambda q: F.struct(q["p"].alias("p"), best(q).alias("d2")))).alias("x")).select(*others, F.col("x.p").alias(axis), "x.d2")
    return d


def feature_transform(px: DataFrame, target: str = "object") -> DataFrame:
    """image_id, row, col, src_row, src_col: the nearest feature (ties: lowest column, then lowest row)."""

    def task(table):
        image, r0, c0, a = raster(table, 0, {"f": ("feature", bool, False), "in": (None, bool, False)})
        r, c = K.nearest_feature(a["f"])
        if not a["f"].any():
            a["in"][:] = False
        return cell_table(image, r0, c0, a["in"], {"src_row": (r + r0).astype(np.int32), "src_col": (c + c0).astype(np.int32)})

    return per_image(features(px, target), task, "image_id long, row int, col int, src_row int, src_col int")


def edt_errors(px: DataFrame, variants: list[str], target: str = "object") -> DataFrame:
    """Cost and error of variants against the exact transform: variant, n_pixels, n_below_exact, n_diff, max_error, mean_error."""
    exact = edt_image(px, target).withColumnRenamed("d2", "exact")
    found = None
    for v in variants:
        one = edt_image(px, target, v).withColumn("variant", F.lit(v))
        found = one if found is None else found.unionByName(one)
    both = found.join(exact, KEY)
    error = F.sqrt("d2") - F.sqrt("exact")
    return both.groupBy("variant").agg(
        F.count(F.lit(1)).alias("n_pixels"), F.sum((F.col("d2") < F.col("exact")).cast("long")).alias("n_below_exact"),
        F.sum((~F.col("d2").eqNullSafe(F.col("exact"))).cast("long")).alias("n_diff"), F.coalesce(F.max(error), F.lit(0.0)).alias("max_error"), F.coalesce(F.avg(error), F.lit(0.0)).alias("mean_error"),
    )


def admissible(errors: DataFrame) -> DataFrame:
    """Whether a variant may replace the raster scan: its errors must not exceed the scan's."""
    base = errors.filter("variant = 'scan4'").select(F.col("max_error").alias("_max"), F.col("mean_error").alias("_mean"))
    return errors.join(F.broadcast(base)).select("variant", ((F.col("max_error") <= F.col("_max")) & (F.col("mean_error") <= F.col("_mean"))).alias("admissible"))


def edt_work(px: DataFrame, variants: list[str], target: str = "object") -> DataFrame:
    """Work counters by variant: variant, pixels, envelope_ops, pushed, queue_high."""

    def task(table):
        import pyarrow as pa

        image, _, _, a = raster(table, 0, {"f": ("feature", bool, False)})
        out = []
        for v in variants:
            work = K.Work()
            if v == "exact":
                K.distance(a["f"], work)
            elif v in ("prop4", "prop8", "prop_exact"):
                K.propagated_distance(a["f"], 4 if v == "prop4" else 8, v == "prop_exact", work)
            else:
                METHODS[v](a["f"])
                work.distance_pixels = 4 * a["f"].size
            out.append((image, v, work.distance_pixels, work.envelope, work.pushed, work.queue_high))
        return pa.table([pa.array(c) for c in zip(*out)], names=["image_id", "variant", "pixels", "envelope_ops", "pushed", "queue_high"])

    rows = per_image(features(px, target), task, "image_id long, variant string, pixels long, envelope_ops long, pushed long, queue_high long")
    return rows.groupBy("variant").agg(F.sum("pixels").alias("pixels"), F.sum("envelope_ops").alias("envelope_ops"), F.sum("pushed").alias("pushed"), F.max("queue_high").alias("queue_high"))
