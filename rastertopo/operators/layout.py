"""Layouts of images and the conversions between them, set algebra on points, frames, halos and runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEY = ["image_id", "row", "col"]


def sparsify(px: DataFrame) -> DataFrame:
    return px.filter("obj").select(*KEY)


def section(px: DataFrame, k: int) -> DataFrame:
    """The cross-section of a grayscale image at level k."""
    return px.withColumn("obj", F.col("level") >= k)


def frames(pt: DataFrame, margin: int = 0) -> DataFrame:
    """The bounding box of each image, widened by ``margin``: image_id, row0, col0, n_rows, n_cols."""
    box = pt.groupBy("image_id").agg(F.min("row").alias("r0"), F.max("row").alias("r1"), F.min("col").alias("c0"), F.max("col").alias("c1"))
    return box.select("image_id", (F.col("r0") - margin).alias("row0"), (F.col("c0") - margin).alias("col0"), (F.col("r1") - F.col("r0") + 1 + 2 * margin).alias("n_rows"), (F.col("c1") - F.col("c0") + 1 + 2 * margin).alias("n_cols"))


def cells(frame: DataFrame) -> DataFrame:
    """All cells of frames."""
    rows = frame.withColumn("row", F.explode(F.sequence("row0", F.col("row0") + F.col("n_rows") - 1)))
    return rows.select("image_id", "row", F.explode(F.sequence("col0", F.col("col0") + F.col("n_cols") - 1)).alias("col"))


def densify(pt: DataFrame, frame: DataFrame) -> DataFrame:
    """Sparse points and their frames to pixels."""
    return cells(frame).join(pt.select(*KEY, F.lit(True).alias("obj")), KEY, "left").withColumn("obj", F.coalesce("obj", F.lit(False)))


def to_rows(px: DataFrame, value: str = "obj") -> DataFrame:
    """Pixels to row vectors: image_id, row, col0, vals."""
    rows = px.groupBy("image_id", "row").agg(F.array_sort(F.collect_list(F.struct("col", F.col(value).alias("v")))).alias("cells"))
    return rows.select("image_id", "row", F.col("cells")[0]["col"].alias("col0"), F.transform("cells", lambda c: c["v"]).alias("vals"))


def from_rows(rw: DataFrame, value: str = "obj") -> DataFrame:
    return rw.select("image_id", "row", "col0", F.posexplode("vals").alias("k", value)).select("image_id", "row", (F.col("col0") + F.col("k")).alias("col"), value)


def transpose(px: DataFrame) -> DataFrame:
    """Rows become columns: a change of names; the shuffle comes with the next operator by row."""
    return px.withColumns({"row": F.col("col"), "col": F.col("row")})


def to_tiles(pt: DataFrame, side: int = 1024) -> DataFrame:
    """Sparse points to packed tiles: image_id, tile_r, tile_c, ones, bits (bitmaps of 32,768 cells by number)."""
    at = pt.withColumns({"tile_r": F.floor(F.col("row") / side).cast("int"), "tile_c": F.floor(F.col("col") / side).cast("int")})
    place = F.pmod("row", F.lit(side)) * side + F.pmod("col", F.lit(side))
    at = at.withColumn("place", place.cast("long"))
    at = at.withColumns({"part": F.expr("place div 32768"), "bit": F.expr("place % 32768")})
    packed = at.groupBy("image_id", "tile_r", "tile_c", "part").agg(F.bitmap_construct_agg("bit").alias("bits"))
    parts = packed.groupBy("image_id", "tile_r", "tile_c")
    return parts.agg(F.sum(F.bitmap_count("bits")).alias("ones"), F.map_from_entries(F.collect_list(F.struct("part", "bits"))).alias("bits")).withColumn("side", F.lit(side))


def from_tiles(tl: DataFrame) -> DataFrame:
    parts = tl.select("image_id", "tile_r", "tile_c", "side", F.explode("bits").alias("part", "bits"))
    byte = parts.select("*", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(4095)), lambda i: F.conv(F.hex(F.substr(F.col("bits"), i + 1, F.lit(1))), 16, 10).cast("int"))).alias("b", "v")).filter("v <> 0")
    bit = byte.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(7)))).filter(F.expr("shiftright(v, k) & 1") == 1)
    place = F.col("part") * 32768 + F.col("b") * 8 + F.col("k")
    bit = bit.withColumn("place", place)
    return bit.select("image_id", (F.col("tile_r") * F.col("side") + F.expr("place div side")).cast("int").alias("row"), (F.col("tile_c") * F.col("side") + F.expr("place % side")).cast("int").alias("col"))


def with_halo(px: DataFrame, side: int, width: int = 1) -> DataFrame:
    """Pixels dealt to tiles of ``side``, each with the strips of ``width`` around it: image_id, tile_r, tile_c, own, row, col, ... Only border pixels are copied."""
    t = {"_r": F.floor(F.col("row") / side).cast("int"), "_c": F.floor(F.col("col") / side).cast("int")}
    at = px.withColumns(t)
    near = lambda x, t: F.array_distinct(F.array(*[F.floor((F.col(x) + d) / side).cast("int") for d in (-width, 0, width)]))
    spread = at.withColumn("tile_r", F.explode(near("row", "_r"))).withColumn("tile_c", F.explode(near("col", "_c")))
    return spread.withColumn("own", (F.col("tile_r") == F.col("_r")) & (F.col("tile_c") == F.col("_c"))).drop("_r", "_c")


def to_runs(pt: DataFrame) -> DataFrame:
    """Maximal horizontal runs of object cells: image_id, row, c0, c1."""
    order = Window.partitionBy("image_id", "row").orderBy("col")
    islands = pt.select(*KEY).withColumn("island", F.col("col") - F.row_number().over(order))
    return islands.groupBy("image_id", "row", "island").agg(F.min("col").alias("c0"), F.max("col").alias("c1")).drop("island")


def complement(pt: DataFrame, frame: DataFrame) -> DataFrame:
    return cells(frame).join(pt.select(*KEY), KEY, "left_anti")


def union(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*KEY).unionByName(b.select(*KEY)).distinct()


def intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*KEY).intersect(b.select(*KEY))


def minus(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*KEY).join(b.select(*KEY), KEY, "left_anti")


def warp(px: DataFrame, matrix: tuple[int, int, int, int], divisor: int, target: DataFrame, offset: tuple[int, int] = (0, 0)) -> DataFrame:
    """Nearest-neighbour affine warp: target cell (r, c) takes the source cell (matrix . (r, c) + offset) div divisor, or background."""
    a, b, c, d = matrix
    at = cells(target).withColumns({"_r": F.floor((F.col("row") * a + F.col("col") * b + offset[0]) / divisor).cast("int"), "_c": F.floor((F.col("row") * c + F.col("col") * d + offset[1]) / divisor).cast("int")})
    source = px.select("image_id", F.col("row").alias("_r"), F.col("col").alias("_c"), "obj")
    return at.join(source, ["image_id", "_r", "_c"], "left").select(*KEY, F.coalesce("obj", F.lit(False)).alias("obj"))


def warp_points(pt: DataFrame, matrix: tuple[int, int, int, int], divisor: int, frame: tuple[int, int, int, int], offset: tuple[int, int] = (0, 0)) -> DataFrame:
    """The object cells of ``warp`` within one frame (row0, col0, n_rows, n_cols) of all images, for a matrix that can be inverted.

    Each target cell has one source cell, so every source cell gives its targets by itself: no join and no shuffle.
    Which of a cell's divisor ** 2 numerators belong to whole targets depends on their remainders by the determinant."""
    a, b, c, d = matrix
    det = a * d - b * c
    n = abs(det)
    fits = lambda u, v: (d * u - b * v) % det == 0 and (a * v - c * u) % det == 0
    pairs = [[(i, j) for i in range(divisor) for j in range(divisor) if fits(u + i, v + j)] for u in range(n) for v in range(n)]
    by_remainder = F.array(*[F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in p]) if p else F.expr("cast(array() as array<struct<i int, j int>>)") for p in pairs])
    u, v = F.col("row") * divisor - offset[0], F.col("col") * divisor - offset[1]
    at = pt.select("image_id", u.alias("_u"), v.alias("_v"))
    at = at.select("image_id", "_u", "_v", F.explode(F.get(by_remainder, F.pmod("_u", F.lit(n)) * n + F.pmod("_v", F.lit(n)))).alias("_p"))
    at = at.select("image_id", (F.col("_u") + F.col("_p.i")).alias("_u"), (F.col("_v") + F.col("_p.j")).alias("_v"))
    out = at.select("image_id", F.expr(f"(_u * {d} - _v * {b}) div {det}").cast("int").alias("row"), F.expr(f"(_v * {a} - _u * {c}) div {det}").cast("int").alias("col"))
    row0, col0, n_rows, n_cols = frame
    return out.filter(F.col("row").between(row0, row0 + n_rows - 1) & F.col("col").between(col0, col0 + n_cols - 1))
