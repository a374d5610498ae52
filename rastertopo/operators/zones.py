"""One image over many tasks: the smoothing filter by bands of rows, in two phases.

An image is cut into bands of ``rows`` rows; two bands are a zone of the published strategy, one its upper and one its
lower half. The state is a row a band: the band's cells packed to bits, line by line, so that the JVM can cut strips of
lines off it. In a phase the bands of one parity work, each on its own cells with one frozen line of either neighbour;
then the others do. Bands that work at once are never adjacent, so what they delete together could go one by one, and
the topology stays. A filter step ends when both phases changed nothing.

Only strips of lines travel to neighbours. Bands are dealt to processors as a schedule says (``processors`` and
``plan``): a processor is a partition, which runs its bands to completion one after the other. No task holds more than
a band and its strips, so an image may be larger than a task's memory; the state is saved after each phase, so a lost
executor costs that phase only."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..plans import schedule as S
from ..plans.lineage import saved
from .blocks import CELLS
from .layout import KEY

#: Lines of a band: a zone of six lines, the least that the strategy allows.
BAND_ROWS = 3
STATE = (
    "image_id long, band int, row0 int, col0 int, n_rows int, n_cols int, proc_id int, "
    "x binary, o binary, c binary, d binary, k binary, p binary, changed long, tests long, ms double"
)
NAMES = [f.strip().split()[0] for f in STATE.split(",")]
FAR32 = (1 << 31) - 1


def packed(a: np.ndarray) -> bytes:
    """A boolean array as bits, each line on bytes of its own."""
    return np.packbits(a, axis=1).tobytes()


def unpacked(data: bytes, n_cols: int) -> np.ndarray:
    stride = (n_cols + 7) // 8
    return np.unpackbits(np.frombuffer(data, np.uint8).reshape(-1, stride), axis=1)[:, :n_cols].astype(bool)


def bands(px: DataFrame, margin: int, rows: int = BAND_ROWS, c: DataFrame | None = None, d: DataFrame | None = None, processors: int | None = None, plan: str = "balanced") -> DataFrame:
    """The state of dense pixels on frames widened by ``margin``: one row for each band, with the processor that runs it."""
    if rows < 1:
        raise ValueError("a band has one line at least")
    marks = px.select(*KEY, F.col("obj").alias("x"))
    for name, points in (("c", c), ("d", d)):
        if points is None:
            marks = marks.withColumn(name, F.lit(False))
        else:
            marks = marks.join(points.select(*KEY, F.lit(True).alias(name)), KEY, "left").withColumn(name, F.coalesce(name, F.lit(False)))
    box = px.groupBy("image_id").agg(
        (F.min("row") - margin).cast("int").alias("top"), (F.max("row") + margin + 1).cast("int").alias("end"),
        (F.min("col") - margin).cast("int").alias("left"), (F.max("col") - F.min("col") + 1 + 2 * margin).cast("int").alias("n_cols"),
    )
    every = box.select("*", F.explode(F.sequence(F.lit(0), F.floor((F.col("end") - F.col("top") - 1) / rows).cast("int"))).alias("band"))
    at = marks.join(box.select("image_id", "top"), "image_id").withColumn("band", F.floor((F.col("row") - F.col("top")) / rows).cast("int")).drop("top")
    frame = saved(every.select("image_id", "band", (F.col("top") + F.col("band") * rows).cast("int").alias("row0"), F.col("left").alias("col0"), F.least(F.lit(rows), F.col("end") - F.col("top") - F.col("band") * rows).cast("int").alias("n_rows"), "n_cols"))

    def build(key, cells, frames):
        import pyarrow as pa

        image, band, row0, col0, n_rows, n_cols = (frames.column(i)[0].as_py() for i in range(6))
        out = {"image_id": image, "band": band, "row0": row0, "col0": col0, "n_rows": n_rows, "n_cols": n_cols, "proc_id": 0, "changed": 0, "tests": 0, "ms": 0.0}
        r, col = cells.column("row").to_numpy() - row0, cells.column("col").to_numpy() - col0
        for name in ("x", "c", "d"):
            a = np.zeros((n_rows, n_cols), bool)
            a[r, col] = cells.column(name).to_numpy(zero_copy_only=False)
            out[name] = packed(a)
        out |= {"o": out["x"], "k": b"", "p": b""}
        return as_table([out])

    state = at.groupBy("image_id", "band").cogroup(frame.groupBy("image_id", "band")).applyInArrow(build, STATE)
    if processors is None:
        return saved(state)
    state = saved(state)
    # The bands of all images in order are the tasks; their number is that of rows of the state.
    order = Window.orderBy("image_id", "band")
    tasks = saved(state.select("image_id", "band", F.octet_length("x").cast("long").alias("cost")).withColumn("task_id", F.row_number().over(order).cast("long") - 1))
    dealt = {"balanced": S.balanced, "symmetric": S.symmetric}[plan](tasks.select("task_id", "cost"), processors)
    dealt = tasks.select("image_id", "band", "task_id").join(dealt.select("task_id", "proc_id"), "task_id").drop("task_id")
    return saved(state.drop("proc_id").join(dealt, ["image_id", "band"]).select(*NAMES))


def as_table(rows: list[dict]):
    import pyarrow as pa

    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary(), "double": pa.float64()}
    return pa.table([pa.array([r[n] for r in rows], kinds[f.strip().split()[1]]) for n, f in zip(NAMES, STATE.split(","))], names=NAMES)


def step(state: DataFrame, operate, depth: int, active: int | None = None, processors: int | None = None) -> DataFrame:
    """``operate(band, x)`` on bands, x being the cells with ``depth`` lines of the neighbours around them.

    ``active``: the parity of the bands that work; the others pass. A band is a dict of its columns, arrays for bits."""
    work = state if active is None else state.filter(F.pmod("band", F.lit(2)) == active)
    heights = state.select("image_id", "band", "n_rows", "n_cols", "proc_id", "x")
    reach = state.agg(F.max("n_rows")).first()[0] or 1
    far = -(-depth // reach)
    parts = []
    for off in [o for o in range(-far, far + 1) if o]:
        # A neighbour above gives its last lines, one below its first; those in between all they have.
        if abs(off) == far and (lines := depth - (far - 1) * reach) < reach:
            cut = F.expr(f"substring(x, 1, {lines} * cast((n_cols + 7) / 8 as int))") if off > 0 else F.expr(f"substring(x, greatest(octet_length(x) - {lines} * cast((n_cols + 7) / 8 as int), 0) + 1)")
        else:
            cut = F.col("x")
        parts.append(heights.select("image_id", (F.col("band") - off).cast("int").alias("band"), F.lit(off).alias("off"), cut.alias("strip")))
    strips = parts[0]
    for p in parts[1:]:
        strips = strips.unionByName(p)
    around = strips.groupBy("image_id", "band").agg(F.array_sort(F.collect_list(F.struct("off", "strip"))).alias("around"))
    ready = work.join(around, ["image_id", "band"], "left")
    if processors is not None:
        ready = ready.repartitionById(processors, "proc_id").sortWithinPartitions("image_id", "band")

    def task(batches):
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                began, n_cols = time.perf_counter(), row["n_cols"]
                lines = {s["off"]: unpacked(s["strip"], n_cols) for s in row["around"] or []}
                own = unpacked(row["x"], n_cols)
                above = [lines[o] for o in sorted(lines) if o < 0]
                below = [lines[o] for o in sorted(lines) if o > 0]
                # Nothing stands beyond the frame, and a short band above the frame's end gives fewer lines.
                top = np.vstack([np.zeros((depth, n_cols), bool), *above])[-depth:]
                end = np.vstack([*below, np.zeros((depth, n_cols), bool)])[:depth]
                band = row | {n: unpacked(row[n], n_cols) if row[n] else None for n in ("o", "c", "d", "k")}
                band["p"] = np.frombuffer(row["p"], np.int32).reshape(-1, n_cols).astype(np.int64) if row["p"] else None
                band["changed"], band["work"] = 0, K.Work()
                x = operate(band, np.vstack([top, own, end]))
                done = row | {n: packed(band[n]) if band[n] is not None else b"" for n in ("o", "c", "d", "k")}
                done |= {"x": packed(x), "p": np.minimum(band["p"], FAR32).astype(np.int32).tobytes() if band["p"] is not None else b""}
                done |= {"changed": band["changed"], "tests": row["tests"] + band["work"].characterised, "ms": row["ms"] + (time.perf_counter() - began) * 1e3}
                out.append(done)
            if out:
                yield as_table(out).to_batches()[0]

    moved = ready.select(*NAMES, "around").mapInArrow(task, STATE)
    return moved if active is None else moved.unionByName(state.filter(F.pmod("band", F.lit(2)) != active).withColumn("changed", F.lit(0).cast("long")))


def middle(a: np.ndarray, depth: int) -> np.ndarray:
    return a[depth : a.shape[0] - depth] if depth else a


def settle(state: DataFrame, operate, processors: int | None, save) -> DataFrame:
    """Both phases in turn until neither changes a cell."""
    while True:
        changed = 0
        for phase in (0, 1):
            state = save(step(state, operate, 1, phase, processors))
            changed += state.agg(F.sum("changed")).first()[0] or 0
        if not changed:
            return state


def thinning(conn: str):
    def operate(band, wide):
        keep = np.ones(wide.shape, bool)
        keep[1:-1] = band["k"]
        order = np.full(wide.shape, K.FAR)
        order[1:-1] = band["p"]
        out = K.thin(wide, keep, order, conn, None, band["work"])
        band["changed"] = int((out != wide).sum())
        return middle(out, 1)

    return operate


def thickening(conn: str):
    def operate(band, wide):
        # The outermost columns are background for good; a column more on either side keeps them testable.
        x = np.pad(wide, ((0, 0), (1, 1)))
        allow, order = np.zeros(x.shape, bool), np.full(x.shape, K.FAR)
        allow[1:-1, 1:-1], order[1:-1, 1:-1] = ~band["k"], band["p"]
        out = K.thicken(x, allow, order, conn, None, band["work"])
        band["changed"] = int((out != x).sum())
        return middle(out[:, 1:-1], 1)

    return operate


def near(of: str, radius: int, limit):
    """Sets a band's priority p, the squared distance to the object ("object") or background within ``radius``, and its
    mask k of cells that stay: ``limit(band, x, p)``."""

    def operate(band, wide):
        features = wide if of == "object" else ~wide
        if of == "background":
            features = np.pad(features, ((0, 0), (radius + 1, radius + 1)), constant_values=True)
        p = K.capped_distance(features, radius)
        if of == "background":
            p = p[:, radius + 1 : -radius - 1]
        p, x = middle(p, radius), middle(wide, radius)
        band["p"], band["k"] = p, limit(band, x, p)
        return x

    return operate


def cut_bands(state: DataFrame, n: int, conn: str, processors: int | None, save) -> DataFrame:
    """Homotopic cutting: thin to the erosion and C, then grow back within the dilation, inside the image before."""
    state = save(step(state, near("background", n, lambda b, x, p: (p == K.FAR) | b["c"]), n, None, processors).withColumn("o", F.col("x")))
    state = settle(state, thinning(conn), processors, save)
    state = save(step(state, near("object", n, lambda b, x, p: ~((p < K.FAR) & b["o"] & ~x)), n, None, processors))
    return settle(state, thickening(conn), processors, save)


def fill_bands(state: DataFrame, n: int, conn: str, processors: int | None, save) -> DataFrame:
    """Homotopic filling: thicken to the dilation without D, then thin to the erosion and the image before."""
    state = save(step(state, near("object", n, lambda b, x, p: ~((p < K.FAR) & ~x & ~b["d"])), n, None, processors).withColumn("o", F.col("x")))
    state = settle(state, thickening(conn), processors, save)
    state = save(step(state, near("background", n, lambda b, x, p: (p == K.FAR) | b["o"]), n, None, processors))
    return settle(state, thinning(conn), processors, save)


def cells(state: DataFrame) -> DataFrame:
    """The object cells of the state."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            for row in batch.to_pylist():
                r, c = np.nonzero(unpacked(row["x"], row["n_cols"]))
                if len(r):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), row["image_id"], np.int64)), pa.array((r + row["row0"]).astype(np.int32)), pa.array((c + row["col0"]).astype(np.int32))], KEY)

    return state.select("image_id", "row0", "col0", "n_cols", "x").mapInArrow(task, CELLS)


def thinned(px: DataFrame, keep: DataFrame | None = None, radius: int = 2, conn: str = "8/4", rows: int = BAND_ROWS, processors: int | None = None, plan: str = "balanced", save=None) -> DataFrame:
    """The state after thinning by bands, nearest to the background first. Kept: ``keep`` and the erosion of ``radius``."""
    save = save or saved
    state = bands(px, 1, rows, keep, None, processors, plan)
    state = save(step(state, near("background", radius, lambda b, x, p: (p == K.FAR) | b["c"]), radius, None, processors))
    return settle(state, thinning(conn), processors, save)


def thin(px: DataFrame, keep: DataFrame | None = None, radius: int = 2, conn: str = "8/4", rows: int = BAND_ROWS, processors: int | None = None, plan: str = "balanced", save=None) -> DataFrame:
    """Thinning by bands over many tasks: object cells."""
    return cells(thinned(px, keep, radius, conn, rows, processors, plan, save))


def filtered(px: DataFrame, n: int, c: DataFrame | None = None, d: DataFrame | None = None, conn: str = "8/4", rows: int = BAND_ROWS, processors: int | None = None, plan: str = "balanced", save=None) -> DataFrame:
    """The state after the homotopic alternating sequential filter of radius 1 to n, by bands over many tasks."""
    save = save or saved
    state = bands(px, n + 2, rows, c, d, processors, plan)
    for radius in range(1, n + 1):
        state = cut_bands(state, radius, conn, processors, save)
        state = fill_bands(state, radius, conn, processors, save)
    return state


def hasf(px: DataFrame, n: int, c: DataFrame | None = None, d: DataFrame | None = None, conn: str = "8/4", rows: int = BAND_ROWS, processors: int | None = None, plan: str = "balanced", save=None) -> DataFrame:
    """The homotopic alternating sequential filter by bands: object cells. Topology as ``homotopic.hasf``, not its bits."""
    return cells(filtered(px, n, c, d, conn, rows, processors, plan, save))


def work_by_band(state: DataFrame) -> DataFrame:
    """image_id, band, proc_id, tests, ms: what each band's task did."""
    return state.select("image_id", "band", "proc_id", "tests", "ms")


def work_by_processor(state: DataFrame) -> DataFrame:
    """proc_id, bands, tests, ms, and ratio_pm: the greatest load over the mean, per mille."""
    load = state.groupBy("proc_id").agg(F.count(F.lit(1)).alias("bands"), F.sum("tests").alias("tests"), F.sum("ms").alias("ms"))
    total = load.agg(F.max("tests").alias("_most"), F.sum("tests").alias("_all"), F.count(F.lit(1)).alias("_n"))
    return load.join(F.broadcast(total)).select("proc_id", "bands", "tests", "ms", F.expr("_most * _n * 1000 div greatest(_all, 1)").alias("ratio_pm"))
