"""Measures: speed-up, efficiency, time shares, cache misses and success rates, topology and quality."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .layout import KEY


def best_of(runs: DataFrame, k: int) -> DataFrame:
    """variant, threads, ms: the least of the first k repetitions."""
    first = Window.partitionBy("variant", "threads").orderBy("rep")
    return runs.withColumn("_k", F.row_number().over(first)).filter(F.col("_k") <= k).groupBy("variant", "threads").agg(F.min("ms").alias("ms"))


def speedup(runs: DataFrame, k: int = 1 << 30) -> DataFrame:
    """variant, threads, speedup: the best sequential time over the best time with so many threads."""
    best = best_of(runs, k)
    one = best.filter("threads = 1").select("variant", F.col("ms").alias("_one"))
    return best.join(one, "variant").select("variant", "threads", (F.col("_one") / F.col("ms")).alias("speedup"))


def efficiency(runs: DataFrame, processors: int | None = None, k: int = 1 << 30) -> DataFrame:
    """Speed-up per processor; by default there is a processor for each thread."""
    by = F.lit(processors) if processors else F.col("threads")
    return speedup(runs, k).withColumn("efficiency", F.col("speedup") / by)


def time_shares(phases: DataFrame) -> DataFrame:
    """size, radius, phase, share_pm of rows (size, radius, phase, ms)."""
    total = Window.partitionBy("size", "radius")
    sums = phases.groupBy("size", "radius", "phase").agg(F.sum("ms").alias("ms"))
    return sums.select("size", "radius", "phase", F.floor(F.col("ms") * 1000 / F.sum("ms").over(total)).cast("long").alias("share_pm"))


def success_rate(misses: DataFrame, base: str, new: str) -> DataFrame:
    """threads, value_pm: 1 - new / base misses of rows (variant, threads, misses), per mille, rounded down."""
    wide = misses.groupBy("threads").pivot("variant", [base, new]).agg(F.sum("misses"))
    return wide.select("threads", F.floor((F.col(base) - F.col(new)) * 1000 / F.col(base)).cast("long").alias("value_pm"))


def efficiency_regions(curve: DataFrame) -> DataFrame:
    """variant, threads, region of miss curves: rising misses are cache-efficient, then a valley where they fall, and
    multithread-efficient once they fell before and rise again."""
    order = Window.partitionBy("variant").orderBy("threads")
    slope = curve.withColumn("d", F.col("misses") - F.lag("misses").over(order))
    fell = F.coalesce(F.max((F.col("d") < 0).cast("int")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    region = F.when(F.col("d").isNull(), "start").when(F.col("d") < 0, "valley").when(fell == 1, "multithread").otherwise("cache")
    return slope.select("variant", "threads", region.alias("region"))


def cache_misses(trace: DataFrame, size: int, ways: int, block: int) -> DataFrame:
    """Misses of a set-associative least-recently-used cache: kind, accesses, misses. ``trace``: seq, address, kind.

    The sets of a cache don't affect each other, so each is replayed in a group of its own, in the order of seq."""
    sets = size // (ways * block)

    def replay(table):
        from collections import Counter, OrderedDict

        import pyarrow as pa

        table = table.sort_by("seq")
        held, seen, missed = OrderedDict(), Counter(), Counter()
        for line, kind in zip(table.column("line").to_pylist(), table.column("kind").to_pylist()):
            seen[kind] += 1
            if line in held:
                held.move_to_end(line)
                continue
            missed[kind] += 1
            held[line] = None
            if len(held) > ways:
                held.popitem(last=False)
        kinds = sorted(seen)
        return pa.table({"kind": pa.array(kinds, pa.string()), "accesses": pa.array([seen[k] for k in kinds], pa.int64()), "misses": pa.array([missed[k] for k in kinds], pa.int64())})

    lines = trace.select("seq", "kind", F.floor(F.col("address") / block).cast("long").alias("line"))
    counts = lines.groupBy(F.pmod("line", F.lit(sets)).alias("set")).applyInArrow(replay, "kind string, accesses long, misses long")
    return counts.groupBy("kind").agg(F.sum("accesses").alias("accesses"), F.sum("misses").alias("misses"))


def private_misses(trace: DataFrame, geometries: tuple) -> DataFrame:
    """Misses of each processor's own cache: size, ways, block, proc_id, kind, accesses, misses.

    Sets of a processor's cache don't affect each other, so each is replayed in a group of its own."""
    def misses(size: int, ways: int, block: int) -> DataFrame:
        line = F.floor(F.col("address") / block).cast("long")
        rows = trace.select("proc_id", "seq", "kind", line.alias("line"), F.pmod(line, F.lit(size // (ways * block))).alias("set"))

        def replay(table):
            from collections import Counter, OrderedDict

            import pyarrow as pa

            table = table.sort_by("seq")
            held, seen, missed = OrderedDict(), Counter(), Counter()
            for at, kind in zip(table.column("line").to_pylist(), table.column("kind").to_pylist()):
                seen[kind] += 1
                missed[kind] += at not in held
                held[at] = None
                held.move_to_end(at)
                if len(held) > ways:
                    held.popitem(last=False)
            kinds, proc = sorted(seen), table.column("proc_id")[0].as_py()
            return pa.table({"proc_id": pa.array([proc] * len(kinds), pa.int32()), "kind": pa.array(kinds, pa.string()), "accesses": pa.array([seen[k] for k in kinds], pa.int64()), "misses": pa.array([missed[k] for k in kinds], pa.int64())})

        counts = rows.groupBy("proc_id", "set").applyInArrow(replay, "proc_id int, kind string, accesses long, misses long")
        sums = counts.groupBy("proc_id", "kind").agg(F.sum("accesses").alias("accesses"), F.sum("misses").alias("misses"))
        return sums.select(F.lit(size).alias("size"), F.lit(ways).alias("ways"), F.lit(block).alias("block"), "proc_id", "kind", "accesses", "misses")

    out = misses(*geometries[0])
    for g in geometries[1:]:
        out = out.unionByName(misses(*g))
    return out


def work_by_zone(zoned: DataFrame) -> DataFrame:
    """zone, work, of_mean_pm: the work of rows (zone, work) by zone, and its ratio to the mean, per mille."""
    sums = zoned.groupBy("zone").agg(F.sum("work").cast("long").alias("work"))
    whole = sums.agg(F.sum("work").alias("_all"), F.count(F.lit(1)).alias("_n"))
    return sums.join(F.broadcast(whole)).select("zone", "work", F.expr("work * 1000 * _n div _all").alias("of_mean_pm"))


def barrier_wait(schedule: DataFrame) -> DataFrame:
    """wait, wait_pm: what processors (proc_id, cost) wait in all at a barrier for the last, and its share, per mille."""
    load = schedule.groupBy("proc_id").agg(F.sum("cost").cast("long").alias("cost"))
    a = load.agg(F.max("cost").alias("m"), F.sum("cost").alias("t"), F.count(F.lit(1)).alias("n"))
    return a.select(F.expr("m * n - t").alias("wait"), F.expr("(m * n - t) * 1000 div (m * n)").alias("wait_pm"))


def efficiency_curve(runs: DataFrame) -> DataFrame:
    """variant, threads, value_pm, dip: efficiency by threads, and where an odd number of threads falls below the next."""
    curve = efficiency(runs).select("variant", "threads", F.floor(F.col("efficiency") * 1000).cast("long").alias("value_pm"))
    after = F.lead("value_pm").over(Window.partitionBy("variant").orderBy("threads"))
    odd = (F.col("threads") % 2 == 1) & (F.col("threads") > 1)
    return curve.withColumn("_after", after).select("variant", "threads", "value_pm", (odd & (F.col("value_pm") < F.col("_after"))).alias("dip"))


def scaling(sizes: DataFrame) -> DataFrame:
    """exponent, r2 of work against size (n, work): the slope of their logarithms."""
    logs = sizes.select(F.log(F.col("n").cast("double")).alias("x"), F.log(F.col("work").cast("double")).alias("y"))
    return logs.agg(F.regr_slope("y", "x").alias("exponent"), F.regr_r2("y", "x").alias("r2"))


def queue_highwater(px: DataFrame) -> DataFrame:
    """image_id, high, blocks: the most cells in the queue of a propagation, and the blocks of a hundredth of the image that hold them."""
    from ..functions import kernels as K
    from .blocks import per_image, raster

    def task(table):
        import pyarrow as pa

        image, _, _, a = raster(table, 0, {"f": ("obj", bool, False)})
        work = K.Work()
        K.propagated_distance(a["f"], 4, work=work)
        block = max(1, a["f"].size // 100)
        return pa.table({"image_id": pa.array([image], pa.int64()), "high": pa.array([work.queue_high], pa.int64()), "blocks": pa.array([-(-work.queue_high // block)], pa.int64())})

    return per_image(px, task, "image_id long, high long, blocks long")


def intensity(counters: DataFrame) -> DataFrame:
    """Adds per_access_pm: computations per memory access, per mille, of rows with ``computed`` and ``accessed``."""
    return counters.withColumn("per_access_pm", F.expr("computed * 1000 div accessed"))


def sampled(rows: DataFrame, share: float) -> DataFrame:
    """The cells (row, col, ...) whose place hashes into the share: the same ones on every run, layout and engine."""
    place = F.md5(F.concat_ws(":", F.col("row").cast("string"), F.col("col").cast("string")))
    return rows.filter(F.conv(F.substring(place, 1, 6), 16, 10).cast("long") < int(share * (1 << 24)))


def cache_sweep(trace: DataFrame, geometries: list[tuple[int, int, int]]) -> DataFrame:
    """Misses by geometry (size, ways, block)."""
    out = None
    for size, ways, block in geometries:
        one = cache_misses(trace, size, ways, block).select(F.lit(size).alias("size"), F.lit(ways).alias("ways"), F.lit(block).alias("block"), "kind", "accesses", "misses")
        out = one if out is None else out.unionByName(one)
    return out


def band_trace(pt: DataFrame, schedule: DataFrame, zone_rows: int, width: int) -> DataFrame:
    """An address trace: processors take turns, each walks the object cells of its zones row by row and reads the rows
    above, at and below; it writes the row itself. ``schedule``: task_id (zone), proc_id, wave."""
    at = pt.withColumn("task_id", F.floor(F.col("row") / zone_rows).cast("long")).join(schedule.select("task_id", "proc_id", "wave"), "task_id")
    turn = F.row_number().over(Window.partitionBy("proc_id").orderBy("wave", "row", "col"))
    at = at.withColumn("turn", turn)
    touch = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(d).alias("d"), F.lit(kind).alias("kind")) for k, (d, kind) in enumerate(((-1, "read"), (0, "read"), (1, "read"), (0, "write")))]))
    at = at.withColumn("_t", touch)
    seq = F.col("turn") * 4096 + F.col("proc_id") * 8 + F.col("_t.k")
    return at.select("proc_id", seq.cast("long").alias("seq"), (((F.col("row") + 1 + F.col("_t.d")) * width + F.col("col")) * 4).cast("long").alias("address"), F.col("_t.kind").alias("kind"))


def topology_check(before: DataFrame, after: DataFrame) -> DataFrame:
    """image_id and the signatures before and after; preserved: whether they agree."""
    b = after.select("image_id", F.col("n_object").alias("obj_after"), F.col("n_background").alias("bg_after"))
    both = before.select("image_id", F.col("n_object").alias("obj_before"), F.col("n_background").alias("bg_before")).join(b, "image_id", "left")
    return both.withColumn("preserved", (F.col("obj_before") == F.col("obj_after")) & (F.col("bg_before") == F.col("bg_after")))


def quality(before: DataFrame, after: DataFrame) -> DataFrame:
    """image_id, n_before, n_after, n_both, iou_pm of two point sets, and the boundary pairs of both."""
    a, b = before.select(*KEY, F.lit(1).alias("a")), after.select(*KEY, F.lit(1).alias("b"))
    both = a.join(b, KEY, "full")
    agree = both.groupBy("image_id").agg(F.count("a").alias("n_before"), F.count("b").alias("n_after"), F.sum((F.col("a").isNotNull() & F.col("b").isNotNull()).cast("long")).alias("n_both"))
    agree = agree.withColumn("iou_pm", F.expr("n_both * 1000 div (n_before + n_after - n_both)"))
    return agree.join(boundary(before).withColumnRenamed("pairs", "edge_before"), "image_id").join(boundary(after).withColumnRenamed("pairs", "edge_after"), "image_id")


def boundary(pt: DataFrame) -> DataFrame:
    """image_id, pairs: object cells beside background cells, counted by edges."""
    cells = pt.select(*KEY)
    sides = F.explode(F.array(*[F.struct(F.lit(r).alias("dr"), F.lit(c).alias("dc")) for r, c in ((0, 0), (-1, 0), (0, 1), (1, 0), (0, -1))]))
    sent = cells.withColumn("_s", sides).select("image_id", (F.col("row") + F.col("_s.dr")).alias("row"), (F.col("col") + F.col("_s.dc")).alias("col"), ((F.col("_s.dr") == 0) & (F.col("_s.dc") == 0)).alias("own"))
    met = sent.groupBy(*KEY).agg(F.max("own").alias("own"), (F.count(F.lit(1)) - F.sum(F.col("own").cast("int"))).alias("n"))
    return met.groupBy("image_id").agg(F.sum(F.when(~F.col("own"), F.col("n")).otherwise(0)).cast("long").alias("pairs"))
