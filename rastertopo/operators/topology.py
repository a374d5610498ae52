"""Digital topology: neighbourhoods, connectivity numbers, simple points, components, signatures, grayscale classes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.lut import EDGES, OFFSETS, PAIRS, dual, numbers, simple
from ..plans.lineage import saved
from .layout import KEY, to_runs


def ball(spark: SparkSession, r: int) -> DataFrame:
    """The Euclidean ball of radius r as offsets: dr, dc, d2. About pi r squared rows, whatever the data."""
    one = spark.range(-r, r + 1).select(F.col("id").cast("int").alias("dr"), F.explode(F.sequence(F.lit(-r), F.lit(r))).alias("dc"))
    return one.withColumn("d2", F.col("dr") * F.col("dr") + F.col("dc") * F.col("dc")).filter(F.col("d2") <= r * r)


def neighbours(pt: DataFrame, n: int = 8, starred: bool = True) -> DataFrame:
    """Each cell with its neighbours nr, nc and the neighbour's bit; not starred: with itself (bit null)."""
    offsets = [(r, c, k) for k, (r, c) in enumerate(OFFSETS) if n == 8 or k in EDGES] + ([] if starred else [(0, 0, None)])
    near = F.explode(F.array(*[F.struct(F.lit(r).alias("dr"), F.lit(c).alias("dc"), F.lit(k).cast("int").alias("k")) for r, c, k in offsets]))
    return pt.withColumn("_o", near).select(*pt.columns, (F.col("row") + F.col("_o.dr")).alias("nr"), (F.col("col") + F.col("_o.dc")).alias("nc"), F.col("_o.k").alias("bit"))


def neighbourhood_mask(px: DataFrame) -> DataFrame:
    """image_id, row, col, obj, mask. Each object pixel sends its bit to its 8 neighbours; bits meet in a partial aggregate."""
    own = px.select(*KEY, F.lit(0).alias("bit"), F.col("obj"), F.lit(True).alias("here"))
    sent = neighbours(px.filter("obj").select(*KEY))
    # The neighbour in direction k sees the sender in the opposite direction.
    sent = sent.select("image_id", F.col("nr").alias("row"), F.col("nc").alias("col"), F.expr("shiftleft(1, (bit + 4) % 8)").alias("bit"), F.lit(False).alias("obj"), F.lit(False).alias("here"))
    met = own.unionByName(sent).groupBy(*KEY).agg(F.bit_or("bit").alias("mask"), F.max("obj").alias("obj"), F.max("here").alias("here"))
    return met.filter("here").select(*KEY, "obj", "mask")


def window_mask(px: DataFrame) -> DataFrame:
    """The same by windows over the rows and columns of dense pixels."""
    across = Window.partitionBy("image_id", "row").orderBy("col")
    down = Window.partitionBy("image_id", "col").orderBy("row")
    bit = lambda c, k: F.coalesce(F.col(c).cast("int"), F.lit(0)) * (1 << k)
    wide = px.withColumns({"w": F.lag("obj").over(across), "e": F.lead("obj").over(across)})
    wide = wide.withColumns({f"{a}{b}": f(c).over(down) for a, f in (("n", F.lag), ("s", F.lead)) for b, c in (("", "obj"), ("w", "w"), ("e", "e"))})
    names = ["n", "ne", "e", "se", "s", "sw", "w", "nw"]
    return wide.select(*KEY, "obj", sum((bit(c, k) for k, c in enumerate(names)), F.lit(0)).alias("mask"))


def _looked_up(values: list, mask: Column, kind: str) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in values]).cast(f"array<{kind}>"), (mask + 1).cast("int"))


def connectivity_number(mask: Column, conn: str = "8/4") -> Column:
    return _looked_up(numbers(conn)[0], mask, "int")


def connectivity_number_bar(mask: Column, conn: str = "8/4") -> Column:
    return _looked_up(numbers(conn)[1], mask, "int")


def is_simple(mask: Column, conn: str = "8/4") -> Column:
    return _looked_up(simple(conn), mask, "boolean")


def simple_points(px: DataFrame, conn: str = "8/4") -> DataFrame:
    return neighbourhood_mask(px).filter(is_simple(F.col("mask"), conn))


def destructible(px: DataFrame, conn: str = "8/4", keep: DataFrame | None = None) -> DataFrame:
    """Object pixels that may be deleted."""
    found = simple_points(px, conn).filter("obj").select(*KEY)
    return found.join(keep.select(*KEY), KEY, "left_anti") if keep is not None else found


def constructible(px: DataFrame, conn: str = "8/4", allow: DataFrame | None = None) -> DataFrame:
    """Background pixels that may be added: simple for the complement."""
    found = simple_points(px, conn).filter("NOT obj").select(*KEY)
    return found.join(allow.select(*KEY), KEY, "left_semi") if allow is not None else found


def contour(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """Object pixels with a background neighbour in the dual adjacency (outside counts as background)."""
    n = PAIRS[conn][1]
    full = sum(1 << k for k in range(8) if n == 8 or k in EDGES)
    return neighbourhood_mask(px).filter(F.col("obj") & (F.col("mask").bitwiseAND(F.lit(full)) != full)).select(*KEY)


def run_adjacency(pt: DataFrame, n: int = 8) -> DataFrame:
    """Runs of successive rows that touch: image_id, row, c0, c1, next_c0, next_c1. An equi-join on (image, row + 1) with an overlap condition."""
    runs = to_runs(pt)
    below = runs.select("image_id", (F.col("row") - 1).alias("row"), F.col("c0").alias("next_c0"), F.col("c1").alias("next_c1"))
    reach = 1 if n == 8 else 0
    return runs.join(below, ["image_id", "row"]).filter((F.col("next_c0") <= F.col("c1") + reach) & (F.col("next_c1") >= F.col("c0") - reach))


def components(pt: DataFrame, n: int = 8, save=None) -> DataFrame:
    """n-components of points of any size: image_id, row, c0, c1, comp (least row * 2**31 + column of the component).

    Runs are the nodes; the least label spreads over touching runs and jumps along labels. ``save`` cuts the lineage of
    each round (default: a table in the checkpoint folder)."""
    save = save or saved
    code = lambda r, c: F.col(r).cast("long") * (1 << 31) + F.col(c)
    runs = to_runs(pt).withColumn("run", code("row", "c0"))
    touch = run_adjacency(pt, n).select("image_id", code("row", "c0").alias("a"), ((F.col("row") + 1).cast("long") * (1 << 31) + F.col("next_c0")).alias("b"))
    both = save(touch.unionByName(touch.select("image_id", F.col("b").alias("a"), F.col("a").alias("b"))))
    labels = save(runs.select("image_id", "run", F.col("run").alias("comp")))
    while True:
        near = both.join(labels.select("image_id", F.col("run").alias("b"), "comp"), ["image_id", "b"]).groupBy("image_id", F.col("a").alias("run")).agg(F.min("comp").alias("near"))
        spread = labels.join(near, ["image_id", "run"], "left").select("image_id", "run", F.col("comp").alias("old"), F.least("comp", F.coalesce("near", "comp")).alias("comp"))
        jump = labels.select("image_id", F.col("run").alias("comp"), F.col("comp").alias("further"))
        new = save(spread.join(jump, ["image_id", "comp"]).select("image_id", "run", "old", F.least("comp", "further").alias("comp")))
        labels = new.select("image_id", "run", "comp")
        if new.filter("old <> comp").isEmpty():
            return runs.join(labels, ["image_id", "run"]).drop("run")


def connected(pt: DataFrame, a: tuple[int, int], b: tuple[int, int], n: int = 8) -> DataFrame:
    """For each image whether an n-path joins a and b."""
    found = components(pt, n)
    of = lambda p: F.max(F.when((F.col("row") == p[0]) & F.lit(p[1]).between(F.col("c0"), F.col("c1")), F.col("comp")))
    return found.groupBy("image_id").agg((of(a) == of(b)).alias("connected")).withColumn("connected", F.coalesce("connected", F.lit(False)))


def euler_number(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """image_id, euler: components less holes, from counts of cells, edges and squares (4-adjacency) or their duals (8)."""
    pt = px.filter("obj").select(*KEY)
    corners = F.explode(F.array(*[F.struct(F.lit(r).alias("dr"), F.lit(c).alias("dc"), F.lit(k).alias("k")) for k, (r, c) in enumerate(((0, 0), (0, 1), (1, 0), (1, 1)))]))
    quads = pt.withColumn("_q", corners).select("image_id", (F.col("row") + F.col("_q.dr")).alias("qr"), (F.col("col") + F.col("_q.dc")).alias("qc"), F.expr("shiftleft(1, _q.k)").alias("bit"))
    quads = quads.groupBy("image_id", "qr", "qc").agg(F.bit_or("bit").alias("m"))
    ones, n = F.bit_count("m"), F.col("m")
    diagonal = n.isin(6, 9)
    sign = -1 if conn == "8/4" else 1
    value = F.sum(F.when(ones == 1, 1).when(ones == 3, -1).when(diagonal, 2 * sign).otherwise(0))
    return quads.groupBy("image_id").agg(F.expr("1").alias("_"), value.alias("q")).select("image_id", F.expr("q div 4").alias("euler"))


def gray_numbers(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """image_id, row, col, level, t_above, t_above_eq, t_below, t_below_eq: connectivity numbers of the neighbours that are
    higher, at least as high (adjacency n), lower, at most as high (dual adjacency). Outside counts as 0."""
    n, m = PAIRS[conn]
    up, down = numbers(conn)[0], numbers(dual(conn))[0]
    sides = gray_sides(px)
    bits = lambda f: sum((F.when(f(F.col(f"l{k}")), 1 << k).otherwise(0) for k in range(8)), F.lit(0))
    own = F.col("level")
    return sides.select(
        *KEY, "level",
        _looked_up(up, bits(lambda x: x > own), "int").alias("t_above"), _looked_up(up, bits(lambda x: x >= own), "int").alias("t_above_eq"),
        _looked_up(down, bits(lambda x: x < own), "int").alias("t_below"), _looked_up(down, bits(lambda x: x <= own), "int").alias("t_below_eq"),
    )


def gray_sides(px: DataFrame) -> DataFrame:
    """Pixels with the levels l0..l7 of their neighbours, 0 outside. Each pixel sends its level to its neighbours."""
    own = px.select(*KEY, "level", F.lit(-1).alias("k"))
    sent = neighbours(px.select(*KEY, "level")).select("image_id", F.col("nr").alias("row"), F.col("nc").alias("col"), "level", ((F.col("bit") + 4) % 8).alias("k"))
    met = own.unionByName(sent).groupBy(*KEY).agg(F.max(F.when(F.col("k") == -1, F.col("level"))).alias("level"), *[F.coalesce(F.max(F.when(F.col("k") == k, F.col("level"))), F.lit(0)).alias(f"l{k}") for k in range(8)])
    return met.filter("level IS NOT NULL")


def gray_class(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """Adds ``kind``: peak, well, interior, separating, destructible, constructible or plain; the first that holds."""
    t = gray_numbers(px, conn)
    kind = (
        F.when(F.col("t_above_eq") == 0, "peak").when(F.col("t_below_eq") == 0, "well")
        .when((F.col("t_below") == 0) & (F.col("t_above") == 0), "interior").when(F.col("t_below") >= 2, "separating")
        .when((F.col("t_above_eq") == 1) & (F.col("t_below") == 1), "destructible").when((F.col("t_above") == 1) & (F.col("t_below_eq") == 1), "constructible").otherwise("plain")
    )
    return t.withColumn("kind", kind)


def gray_step(px: DataFrame, conn: str = "8/4", direction: str = "lower", subfield: int = 0) -> DataFrame:
    """One step: the destructible pixels of a parity subfield sink to the highest strictly lower neighbour ("raise": the
    constructible ones rise to the lowest strictly higher one)."""
    sides = gray_sides(px).join(gray_numbers(px, conn).drop("level"), KEY)
    here = (F.pmod("row", F.lit(2)) * 2 + F.pmod("col", F.lit(2))) == subfield
    near = [F.col(f"l{k}") for k in range(8)]
    own = F.col("level")
    if direction == "lower":
        goes = (F.col("t_above_eq") == 1) & (F.col("t_below") == 1)
        to = F.array_max(F.array(*[F.when(x < own, x) for x in near]))
    else:
        goes = (F.col("t_above") == 1) & (F.col("t_below_eq") == 1)
        to = F.array_min(F.array(*[F.when(x > own, x) for x in near]))
    return sides.select(*KEY, F.when(here & goes, to).otherwise(own).alias("level"))
