"""Homotopic thinning, thickening, cutting, filling and the smoothing filter on DataFrames.

Two strategies. "image": one shuffle by image, the whole filter in one task per image; the default while an image fits.
"tile": the image is dealt to square tiles that work in four colours with a frozen one-pixel halo, in super-steps until
nothing changes; only changed borders make further work. Both keep the topology; "image" is canonical bit by bit."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import gray as G
from ..functions import kernels as K
from .blocks import CELLS, cell_table, per_image, raster
from ..plans.lineage import saved
from .layout import KEY, with_halo
from .topology import is_simple, neighbourhood_mask

#: Pixels of a frame that one task takes.
IMAGE_PIXELS = 16_000_000


def with_constraints(px: DataFrame, c: DataFrame | None = None, d: DataFrame | None = None) -> DataFrame:
    """Pixels with columns in_c and in_d: the object cells to keep and the background cells to leave."""
    for name, points in (("in_c", c), ("in_d", d)):
        if points is None:
            px = px.withColumn(name, F.lit(False))
        else:
            px = px.join(points.select(*KEY, F.lit(True).alias(name)), KEY, "left").withColumn(name, F.coalesce(name, F.lit(False)))
    return px.select(*KEY, "obj", "in_c", "in_d")


def run(px: DataFrame, operate, margin: int, c: DataFrame | None = None, d: DataFrame | None = None) -> DataFrame:
    """``operate(x, c, d)`` on each image, padded by ``margin``; padded by more where the outermost ring was reached."""
    bare = c is None and d is None

    def task(table):
        wide = margin
        while True:
            columns = {"x": ("obj", bool, False)}
            if not bare:
                columns |= {"c": ("in_c", bool, False), "d": ("in_d", bool, False)}
            image, r0, c0, a = raster(table, wide, columns)
            out = operate(a["x"], a.get("c"), a.get("d"))
            ring = out.copy()
            ring[1:-1, 1:-1] = False
            if wide == 0 or not ring.any():
                return cell_table(image, r0, c0, out)
            wide *= 2

    return per_image(px.select(*KEY, "obj") if bare else with_constraints(px, c, d), task, CELLS)


def thin(px: DataFrame, keep: DataFrame | None = None, conn: str = "8/4", keep_radius: int | None = None, max_steps: int | None = None) -> DataFrame:
    """Constrained thinning, nearest to the background first. Kept: ``keep`` and, with ``keep_radius``, the erosion."""

    def operate(x, c, _):
        d = K.distance(~x) if keep_radius is None else K.capped_distance(~x, keep_radius)
        return K.thin(x, K.union_keep(c, None if keep_radius is None else d == K.FAR), d, conn, max_steps)

    return run(px, operate, 1, keep)


def skeleton(px: DataFrame, conn: str = "8/4") -> DataFrame:
    return thin(px, None, conn)


def thicken(px: DataFrame, radius: int, avoid: DataFrame | None = None, conn: str = "8/4", max_steps: int | None = None) -> DataFrame:
    """Constrained thickening within the dilation of ``radius``, nearest to the object first; ``avoid`` cells stay background."""

    def operate(x, _, d):
        outer = K.capped_distance(x, radius)
        allow = (outer < K.FAR) & ~x
        return K.thicken(x, allow & ~d if d is not None else allow, outer, conn, max_steps)

    return run(px, operate, radius + 1, None, avoid)


def cut(px: DataFrame, n: int, c: DataFrame | None = None, conn: str = "8/4") -> DataFrame:
    """The homotopic cutting (opening only)."""
    return run(px, lambda x, keep, _: K.cut(x, n, keep, conn), n + 1, c)


def fill(px: DataFrame, n: int, d: DataFrame | None = None, conn: str = "8/4") -> DataFrame:
    """The homotopic filling (closing only)."""
    return run(px, lambda x, _, leave: K.fill(x, n, leave, conn), n + 1, None, d)


def hasf(px: DataFrame, n: int, c: DataFrame | None = None, d: DataFrame | None = None, conn: str = "8/4") -> DataFrame:
    """The homotopic alternating sequential filter with constraints: cut and fill of radius 1 to n."""
    return run(px, lambda x, keep, leave: K.hasf(x, n, keep, leave, conn), n + 1, c, d)


def smooth(px: DataFrame, n: float, conn: str = "8/4", stop_after: int | None = None) -> DataFrame:
    """The filter with the radius as its only parameter. ``n`` may be infinite: radii until the frame's diagonal, or
    until ``stop_after`` radii in a row changed nothing (a shortcut that proves nothing about later radii)."""
    if n != float("inf"):
        return hasf(px, int(n), conn=conn)

    def operate(x, *_):
        quiet, reach = 0, int(np.hypot(*x.shape)) + 1
        for r in range(1, reach + 1):
            wide = np.pad(x, r + 1)
            y = K.fill(K.cut(wide, r, None, conn), r, None, conn)[r + 1 : -r - 1, r + 1 : -r - 1]
            quiet = quiet + 1 if (y == x).all() else 0
            x = y
            if stop_after and quiet >= stop_after:
                break
            if quiet and not K.capped_distance(~np.pad(x, 1), r).max(initial=0) == K.FAR and not (K.capped_distance(x, r) == K.FAR).any():
                break
        return x

    return run(px, operate, 16)


def control(px: DataFrame, image: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The constraints that a control image implies: its cells in the object, and its cells in the background."""
    both = px.select(*KEY, "obj").join(image.select(*KEY), KEY, "left_semi")
    return both.filter("obj").select(*KEY), both.filter("NOT obj").select(*KEY)


def work(px: DataFrame, n: int, conn: str = "8/4") -> DataFrame:
    """image_id and what the filter did: characterised, changed, steps, distance_pixels, pushed."""
    names = ["characterised", "changed", "steps", "distance_pixels", "pushed"]

    def task(table):
        import pyarrow as pa

        image, _, _, a = raster(table, n + 1, {"x": ("obj", bool, False)})
        done = K.Work()
        K.hasf(a["x"], n, conn=conn, work=done)
        return pa.table({"image_id": pa.array([image], pa.int64()), **{k: pa.array([getattr(done, k)], pa.int64()) for k in names}})

    return per_image(px, task, "image_id long, " + ", ".join(f"{k} long" for k in names))


def thin_unsafe(px: DataFrame, conn: str = "8/4", keep: DataFrame | None = None) -> DataFrame:
    """The negative baseline: all simple points go at once."""
    marked = neighbourhood_mask(px).filter("obj")
    gone = marked.filter(is_simple(F.col("mask"), conn)).select(*KEY)
    if keep is not None:
        gone = gone.join(keep.select(*KEY), KEY, "left_anti")
    return marked.select(*KEY).join(gone, KEY, "left_anti")


def critical_points(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """Simple points that can't all go together: of them, those that one sweep by parity subfields, each rechecked, leaves."""
    state = px.select(*KEY, "obj")
    first = neighbourhood_mask(state).filter(F.col("obj") & is_simple(F.col("mask"), conn)).select(*KEY)
    state = state.join(first.withColumn("simple", F.lit(True)), KEY, "left").withColumn("simple", F.coalesce("simple", F.lit(False)))
    for s in range(4):
        masks = neighbourhood_mask(state.select(*KEY, "obj")).select(*KEY, "mask")
        here = (F.pmod("row", F.lit(2)) * 2 + F.pmod("col", F.lit(2))) == s
        state = state.join(masks, KEY).withColumn("obj", F.col("obj") & ~(here & F.col("simple") & is_simple(F.col("mask"), conn))).drop("mask")
    return state.filter("obj AND simple").select(*KEY)


def zone_thin(px: DataFrame, radius: int | None = None, conn: str = "8/4", half_rows: int = 3) -> DataFrame:
    """Thinning by row bands whose halves work in turn. Kept: the erosion of ``radius``."""

    def operate(x, *_):
        d = K.distance(~x) if radius is None else K.capped_distance(~x, radius)
        return K.zone_thin(x, None if radius is None else d == K.FAR, d, conn, half_rows)

    return run(px, operate, 1)


def thin_tiles(px: DataFrame, keep: DataFrame | None = None, conn: str = "8/4", side: int = 1024, save=None) -> DataFrame:
    """Thinning of images of any size. Tiles of a colour are ``side`` apart, so their borders never work at once.

    State: dense pixels with obj and keep. ``save`` cuts the lineage of a super-step (default: a table in the checkpoint folder)."""
    save = save or saved
    state = with_constraints(px, keep).select(*KEY, "obj", F.col("in_c").alias("keep")).withColumn("changed", F.lit(True))
    schema = CELLS + ", obj boolean, keep boolean, changed boolean"

    def tile(key, table):
        import pyarrow as pa

        image, r0, c0, a = raster(table, 0, {"x": ("obj", bool, False), "k": ("keep", bool, True), "own": ("own", bool, False)})
        free = a["own"] & ~a["k"]
        out = K.thin(a["x"], ~free, K.distance(~np.pad(a["x"], 1))[1:-1, 1:-1], conn)
        rows, cols = np.nonzero(a["own"])
        gone = (a["x"] & ~out)[rows, cols]
        return pa.table({"image_id": pa.array(np.full(len(rows), image, np.int64)), "row": pa.array((rows + r0).astype(np.int32)), "col": pa.array((cols + c0).astype(np.int32)), "obj": pa.array(out[rows, cols]), "keep": pa.array(a["k"][rows, cols]), "changed": pa.array(gone)})

    while True:
        moved = False
        for colour in range(4):
            dealt = with_halo(state.drop("changed"), side)
            mine = (F.pmod("tile_r", F.lit(2)) * 2 + F.pmod("tile_c", F.lit(2))) == colour
            active = dealt.filter(mine).groupBy("image_id", "tile_r", "tile_c").applyInArrow(tile, schema)
            rest = dealt.filter(~mine & F.col("own")).select(*KEY, "obj", "keep", F.lit(False).alias("changed"))
            state = save(active.unionByName(rest))
            moved = moved or not state.filter("changed").isEmpty()
        if not moved:
            return state.filter("obj").select(*KEY)


def gray(px: DataFrame, operate) -> DataFrame:
    """A grayscale array operator on each image: image_id, row, col, level."""

    def task(table):
        image, r0, c0, a = raster(table, 0, {"f": ("level", np.int64, 0), "in": (None, bool, False)})
        return cell_table(image, r0, c0, a["in"], {"level": operate(a["f"]).astype(np.int32)})

    return per_image(px.select(*KEY, "level"), task, CELLS + ", level int")


def gray_kernel(px: DataFrame, conn: str = "8/4") -> DataFrame:
    return gray(px, lambda f: G.gray_kernel(f, conn)[0])


def leveling_kernel(px: DataFrame, height: int, conn: str = "8/4") -> DataFrame:
    return gray(px, lambda f: G.gray_kernel(f, conn, height=height)[0])


def gray_skeleton(px: DataFrame, conn: str = "8/4") -> DataFrame:
    return gray(px, lambda f: G.gray_skeleton(f, conn))


def restore_crests(px: DataFrame, rounds: int = 1, conn: str = "8/4") -> DataFrame:
    return gray(px, lambda f: G.restore_crests(f, conn, rounds))


def watershed(px: DataFrame, conn: str = "8/4") -> DataFrame:
    return gray(px, lambda f: G.watershed(f, conn))


def topology_signature(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """image_id, n_object, n_background: component counts (the outside belongs to the background)."""

    def task(table):
        import pyarrow as pa

        image, _, _, a = raster(table, 0, {"x": ("obj" if "obj" in table.column_names else None, bool, False)})
        n, m = K.signature(a["x"], conn)
        return pa.table({"image_id": pa.array([image], pa.int64()), "n_object": pa.array([n], pa.int64()), "n_background": pa.array([m], pa.int64())})

    return per_image(px, task, "image_id long, n_object long, n_background long")


def component_cells(px: DataFrame, n: int = 8) -> DataFrame:
    """Object cells with comp: the least row-major index of the component in the image's frame of ``width`` columns."""

    def task(table):
        image, r0, c0, a = raster(table, 0, {"x": ("obj" if "obj" in table.column_names else None, bool, False)})
        return cell_table(image, r0, c0, a["x"], {"comp": K.label(a["x"], n).astype(np.int64)})

    return per_image(px, task, CELLS + ", comp long")


def section_counts(px: DataFrame, conn: str = "8/4") -> DataFrame:
    """image_id, k, n_object, n_background of every section F >= k, k from 1 to the highest level of the image."""

    def task(table):
        import pyarrow as pa

        image, _, _, a = raster(table, 0, {"f": ("level", np.int64, 0)})
        rows = [(image, k, *K.signature(a["f"] >= k, conn)) for k in range(1, int(a["f"].max()) + 1)]
        return pa.table([pa.array(c, pa.int64()) for c in (zip(*rows) if rows else [[]] * 4)], names=["image_id", "k", "n_object", "n_background"])

    return per_image(px.select(*KEY, "level"), task, "image_id long, k long, n_object long, n_background long")




#: Cells of the images that one array holds when images are stacked.
STACK_CELLS = 1 << 20


def stacked_preserved(images: list[np.ndarray], n: int, conn: str = "8/4") -> np.ndarray:
    """For each image whether the filter of radius ``n`` keeps its signature, all filtered as one array: images lie apart by
    more than the filter reaches, at even places, so each is filtered as by itself."""
    gap = margin = 2 * n + 2
    while True:
        width = max((x.shape[1] for x in images), default=0) + 2 * margin
        heights = [x.shape[0] + x.shape[0] % 2 + gap for x in images]
        tops = np.cumsum([margin, *heights])
        x = np.zeros((int(tops[-1]) + margin, width), bool)
        owner = np.repeat(np.arange(len(images) + 1), np.diff([0, *(tops[1:] - gap // 2), len(x)]))
        for top, image in zip(tops, images):
            x[top : top + image.shape[0], margin : margin + image.shape[1]] = image
        y = K.hasf(x, n, conn=conn)
        free = np.ones(x.shape, bool)
        for top, image in zip(tops, images):
            free[top - gap // 2 + 1 : top + image.shape[0] + gap // 2 - 1, 1:-1] = False
        if not (y & free).any():
            break
        gap, margin = 2 * gap, 2 * margin
    before, after = (K.signatures(z, owner, len(images) + 1, conn)[:-1] for z in (x, y))
    return (before == after).all(axis=1)


def texts_preserved(docs: DataFrame, text_col: str, n: int, carried: list[str], width: int = 128, conn: str = "8/4") -> DataFrame:
    """The ``carried`` columns of each row, and whether the filter keeps the topology of its text as an image of ``width``
    columns (a null text is empty). Texts become images within the task that reads them; no pixel is shuffled."""
    # A file of one row group would be one task.
    docs = docs.select(*carried, F.col(text_col)).repartition(4 * docs.sparkSession.sparkContext.defaultParallelism)
    fields = docs.schema

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            done, images, cells = [], [], 0
            for text in batch.column(len(carried)):
                codes = np.frombuffer((text.as_py() or "").encode("utf-32-le", "surrogatepass"), np.uint32)
                flat = np.zeros(-(-len(codes) // width) * width, bool)
                flat[: len(codes)] = (codes != 32) & (codes != 10)
                images.append(flat.reshape(-1, width))
                cells += len(flat)
                if cells >= STACK_CELLS:
                    done.append(stacked_preserved(images, n, conn))
                    images, cells = [], 0
            done.append(stacked_preserved(images, n, conn))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(np.concatenate(done))], [*carried, "preserved"])

    return docs.mapInArrow(task, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in fields.fields[:-1]), "preserved boolean"]))


def rows_preserved(rows: DataFrame, change, n: int, conn: str = "8/4") -> DataFrame:
    """image_id, preserved: whether the filter keeps the topology of ``change`` of each image of rows (image_id, row, vals), whose positive
    values are the object. Only row vectors are shuffled."""

    def task(table):
        import pyarrow as pa

        lengths = table.column("vals").combine_chunks().value_lengths().to_pylist()
        at = table.column("row").to_pylist()
        x = np.zeros((max(at) + 1, max(1, *(k or 0 for k in lengths))), bool)
        for row, vals in zip(at, table.column("vals").to_pylist()):
            x[row, : len(vals or ())] = [v is not None and v > 0 for v in vals or ()]
        return pa.table({"image_id": table.column("image_id").slice(0, 1), "preserved": pa.array(stacked_preserved([change(x)], n, conn))})

    return per_image(rows, task, "image_id long, preserved boolean")
