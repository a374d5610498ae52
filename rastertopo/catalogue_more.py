"""Further queries of the catalogue: bands of one image over many tasks, the generic loop, measures of runs, streams, surface."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import oracle as O
from .catalogue import KEY, SIGNED, TASKS, ZONED, BLOCKS, _merge_round, checked, document_tasks, query, row_runs, run_sql, with_
from .functions import generic
from .functions import kernels as K
from .operators import layout as L
from .operators import measures as M
from .operators import topology as T
from .operators import zones as Z
from .operators.blocks import transform
from .plans import schedule as S
from .plans.lineage import folder
from .sources import rasters as R

# ---- one image over many tasks ----


@query("thin_zones_signature", SIGNED)
def _(s, d):
    px = R.embeddings(s, d)
    return checked(px, Z.thin(px, radius=2, rows=6))


@query("hasf_zones_signature", SIGNED)
def _(s, d):
    px = R.embeddings(s, d)
    return checked(px, Z.hasf(px, 1, rows=16, processors=4))


@query("bench_thin_schedulers")
def _(s, d):
    """Thinning of the 200 x 200 raster by bands under both schedulers: the work of each processor."""
    pt = R.orders(s, d).select(*KEY)
    px = L.densify(pt, L.frames(pt))
    out = None
    for plan in ("balanced", "symmetric"):
        one = Z.work_by_processor(Z.thinned(px, rows=6, processors=8, plan=plan)).select(F.lit(plan).alias("scheduler"), "proc_id", "bands", "tests", "ratio_pm")
        out = one if out is None else out.unionByName(one)
    return out


# ---- the generic loop ----


@query("stabilise_skeleton_recheck8", SIGNED)
def _(s, d):
    px = R.embeddings(s, d)
    return checked(px, transform(px, lambda x: generic.skeleton(x), 1))


@query("stabilise_skeleton_recheck4", SIGNED)
def _(s, d):
    px = R.embeddings(s, d)
    return checked(px, transform(px, lambda x: generic.skeleton(x, recheck=4), 1))


@query("stabilise_leftovers", with_(O.RE) + "SELECT image_id, 0::BIGINT AS n FROM re GROUP BY 1")
def _(s, d):
    """Points that the loop with four rechecked neighbours leaves deletable: none, as a full scan ends it."""
    px = R.embeddings(s, d)
    thin = transform(px, lambda x: generic.skeleton(x, recheck=4), 1).withColumn("o", F.lit(True))
    after = px.select(*KEY).join(thin, KEY, "left").select(*KEY, F.coalesce("o", F.lit(False)).alias("obj"))
    left = T.neighbourhood_mask(after).filter(F.col("obj") & T.is_simple(F.col("mask"), "8/4")).groupBy("image_id").agg(F.count(F.lit(1)).alias("n"))
    return px.select("image_id").distinct().join(left, "image_id", "left").select("image_id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


# ---- measures of runs ----


@query("work_by_zone", with_(O.RL, "z AS (SELECT (row // 64)::BIGINT AS zone, count(*) AS work FROM rl GROUP BY 1)") + "SELECT zone, work, work * 1000 * (SELECT count(*) FROM z) // (SELECT sum(work) FROM z)::BIGINT AS of_mean_pm FROM z")
def _(s, d):
    zoned = R.lineitem(s, d).withColumn("zone", F.expr("row div 64"))
    return M.work_by_zone(zoned.withColumn("work", F.lit(1)))


@query("barrier_wait", with_(TASKS, BLOCKS, "l AS (SELECT 'balanced' AS scheduler, k % 8 AS p, sum(cost) AS c FROM tk GROUP BY 1, 2 UNION ALL SELECT 'symmetric', proc_id, sum(cost) FROM bl GROUP BY 1, 2)") + "SELECT scheduler, (max(c) * 8 - sum(c))::BIGINT AS wait, ((max(c) * 8 - sum(c)) * 1000 // (max(c) * 8))::BIGINT AS wait_pm FROM l GROUP BY 1")
def _(s, d):
    tasks = document_tasks(s, d)
    one = lambda name, x: M.barrier_wait(x).select(F.lit(name).alias("scheduler"), "wait", "wait_pm")
    return one("balanced", S.balanced(tasks, 8)).unionByName(one("symmetric", S.symmetric(tasks, 8)))


@query("round_robin_blocks", with_(TASKS) + "SELECT task_id, cost, ((k // 4) % 8)::INT AS proc_id FROM tk")
def _(s, d):
    """Clock-driven: the processors take turns by slices of four tasks, whatever their cost."""
    return S.clocked(document_tasks(s, d), 8, 4)


@query("schedule_staircase", with_(TASKS) + "SELECT task_id, cost, CASE WHEN k // 8 % 2 = 0 THEN k % 8 ELSE 7 - k % 8 END::INT AS proc_id FROM tk")
def _(s, d):
    """A rotating staircase: the order of the processors turns round at each wave."""
    return S.staircase(document_tasks(s, d), 8)


CURVE_THREADS = (1, 2, 3, 4, 5, 8, 16)


@query("efficiency_curve_sample", with_(O.RL, run_sql(CURVE_THREADS, 1), "e AS (SELECT c.variant, c.threads, floor(o.ms / c.ms / c.threads * 1000)::BIGINT AS value_pm FROM rn c JOIN rn o ON o.variant = c.variant AND o.threads = 1)") + "SELECT *, threads % 2 = 1 AND threads > 1 AND value_pm < lead(value_pm) OVER (PARTITION BY variant ORDER BY threads) AS dip FROM e")
def _(s, d):
    return M.efficiency_curve(row_runs(s, d, CURVE_THREADS, 1))


@query("scaling_of_distance", "SELECT 'pixels' AS counter, 1.0::DOUBLE AS exponent")
def _(s, d):
    """The growth of the exact transform's work with the number of pixels, from four corners of RL: linear."""
    cells = R.lineitem(s, d).filter("row < 128 AND col < 128").select("row", "col")
    sides = F.array(*[F.lit(k) for k in (16, 32, 64, 128)])

    def task(table):
        import pyarrow as pa

        work, side = K.Work(), table.column("side")[0].as_py()
        x = np.zeros((side, side), bool)
        rows, cols = table.column("row").to_numpy(), table.column("col").to_numpy()
        x[rows[rows >= 0], cols[rows >= 0]] = True
        K.distance(x, work)
        return pa.table({"n": pa.array([side * side], pa.int64()), "work": pa.array([work.distance_pixels], pa.int64())})

    corners = cells.withColumn("side", F.explode(sides)).filter("row >= 0 AND col >= 0 AND row < side AND col < side").select("side", "row", "col")
    # A corner without a cell is an image, too.
    corners = corners.unionByName(s.range(1).select(F.explode(sides).alias("side"), F.lit(-1).alias("row"), F.lit(-1).alias("col")))
    return M.scaling(corners.groupBy("side").applyInArrow(task, "n long, work long")).select(F.lit("pixels").alias("counter"), F.round("exponent", 6).alias("exponent"))


@query("queue_highwater")
def _(s, d):
    """The most cells that a propagation's queue holds, against the blocks of a hundredth of the image that it would take."""
    return M.queue_highwater(R.embeddings(s, d))


@query("compute_intensity", with_(O.RL) + "SELECT (row // 64)::BIGINT AS zone, count(*) AS cells, (count(*) * 8 * 1000 // (count(*) * 4))::BIGINT AS per_access_pm FROM rl GROUP BY 1")
def _(s, d):
    zoned = R.lineitem(s, d).groupBy(F.expr("row div 64").alias("zone")).agg(F.count(F.lit(1)).alias("cells"))
    return M.intensity(zoned.withColumn("computed", F.col("cells") * 8).withColumn("accessed", F.col("cells") * 4)).select("zone", "cells", "per_access_pm")


@query("cache_geometries")
def _(s, d):
    """Misses of each processor's own caches: two first-level and one second-level geometry of the published machines."""
    pt = R.orders(s, d).select(*KEY)
    tasks = s.range(25).select(F.col("id").alias("task_id"), F.lit(1).cast("long").alias("cost"))
    out = None
    for name, plan in (("balanced", S.balanced(tasks, 4)), ("symmetric", S.symmetric(tasks, 4))):
        one = M.private_misses(M.band_trace(pt, plan, 8, 256), ((16384, 8, 64), (32768, 8, 64), (524288, 16, 64))).select(F.lit(name).alias("scheduler"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# ---- streams ----


@query("stream_control_join", with_(O.RO) + "SELECT event_type, count(*) AS n FROM events WHERE EXISTS (SELECT 1 FROM ro WHERE ro.row = user_id % 168 AND ro.col = (hour(ts) * 60 + minute(ts)) // 5) GROUP BY 1")
def _(s, d):
    from .streaming.events import stream
    from .streaming.stateful import controlled, rows_of

    return rows_of(s, controlled(stream(s, d), R.orders(s, d)), "complete")


@query("stream_finish_merge", with_(O.RL, ZONED, "w AS (SELECT node, row_number() OVER (ORDER BY finish, node) - 1 AS k FROM zo), r1 AS (SELECT k // 2 AS child, max(node) FILTER (k % 2 = 0) AS p1, max(node) FILTER (k % 2 = 1) AS p2 FROM w GROUP BY 1)") + """SELECT 0::BIGINT AS image_id, 1 AS round, child::INT AS child, p1, p2 FROM r1
UNION ALL SELECT 0, 2, g::INT, 2 * g, 2 * g + 1 FROM range(2) x(g) UNION ALL SELECT 0, 3, 0, 0, 1""")
def _(s, d):
    from .streaming.stateful import finish_merge, left_alone, rows_of

    workers = R.lineitem(s, d).groupBy(F.expr("row div 64").alias("worker_id")).agg(F.count(F.lit(1)).alias("finish")).withColumn("image_id", F.lit(0).cast("long"))
    path = f"{folder(s)}/merge-{pd.Timestamp.now().value}"
    workers.coalesce(1).write.parquet(path)
    pairs = rows_of(s, finish_merge(s.readStream.schema(workers.schema).parquet(path)), "append")
    return pairs.unionByName(left_alone(pairs, s.read.schema(workers.schema).parquet(path)))


@query("stream_tile_filter", with_(O.RE, "t AS (SELECT image_id, (row // 32)::INT AS tile_r, (col // 32)::INT AS tile_c, count(*) FILTER (obj) AS n FROM re GROUP BY 1, 2, 3)") + "SELECT image_id, tile_r, tile_c, 1::INT AS version, n AS n_before FROM t")
def _(s, d):
    from .streaming.stateful import rows_of, tile_filter

    px = R.embeddings(s, d).select(*KEY, "obj")
    path = f"{folder(s)}/tiles-{pd.Timestamp.now().value}"
    px.write.parquet(path)
    return rows_of(s, tile_filter(s.readStream.schema(px.schema).parquet(path), 32, 1), "update").drop("n_after")


@query("stream_closed_days", "SELECT strftime(ts, '%Y-%m-%d') AS day, (user_id % 168)::INT AS row, ((hour(ts) * 60 + minute(ts)) // 5)::INT AS col, count(*) AS n FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events) GROUP BY 1, 2, 3")
def _(s, d):
    from .streaming.events import stream
    from .streaming.stateful import late_cells, rows_of

    return rows_of(s, late_cells(stream(s, d)), "append")


# ---- surface ----


def _trip(s, df: DataFrame, kind: str) -> DataFrame:
    path = f"{folder(s)}/trip-{kind}-{pd.Timestamp.now().value}"
    df.write.format(kind).save(path)
    return s.read.format(kind).schema(df.schema).load(path)


def _round_trip(kind: str) -> None:
    @query(f"roundtrip_{kind}", with_(O.RO) + "SELECT * FROM ro")
    def _(s, d):
        return _trip(s, R.orders(s, d), kind)


for _kind in ("csv", "json", "orc", "parquet"):
    _round_trip(_kind)


@query("tile_sink", with_(O.RL) + "SELECT (row // 128)::INT AS tile_r, (col // 128)::INT AS tile_c, count(*) AS ones FROM rl GROUP BY 1, 2")
def _(s, d):
    """Packed tiles written as Parquet in folders by tile row, and one pruned read of each."""
    tiles = L.to_tiles(R.lineitem(s, d).select(*KEY), 128)
    path = f"{folder(s)}/tiles-{pd.Timestamp.now().value}"
    tiles.write.partitionBy("tile_r").parquet(path)
    return s.read.schema(tiles.schema).parquet(path).select("tile_r", "tile_c", "ones")


@query("hash_join_neighbours", with_(O.RE) + "SELECT a.image_id, a.col, count(*) AS pairs FROM re a JOIN re b ON a.image_id = b.image_id AND a.col = b.col AND b.row = a.row + 1 WHERE a.obj AND b.obj GROUP BY 1, 2")
def _(s, d):
    pt = L.sparsify(R.embeddings(s, d))
    below = pt.select("image_id", (F.col("row") - 1).alias("row"), "col")
    return pt.join(below.hint("shuffle_hash"), KEY).groupBy("image_id", "col").agg(F.count(F.lit(1)).alias("pairs"))


@query("recursive_halves", f"WITH RECURSIVE z AS (SELECT 0 AS depth, 0 AS r0, 512 AS n UNION ALL SELECT depth + 1, r0 + h * (n // 2), n // 2 FROM z, (VALUES (0), (1)) v(h) WHERE n > 64), {O.RL} SELECT depth::INT AS depth, r0::INT AS r0, z.n::INT AS n, count(rl.row) AS cells FROM z LEFT JOIN rl ON rl.row >= r0 AND rl.row < r0 + z.n GROUP BY 1, 2, 3")
def _(s, d):
    """Zones of RL by recursive halving of its rows, each with its object cells."""
    halves = s.sql("WITH RECURSIVE z(depth, r0, n) AS (SELECT 0, 0, 512 UNION ALL SELECT depth + 1, cast(r0 + h * (n div 2) AS INT), cast(n div 2 AS INT) FROM z CROSS JOIN (VALUES (0), (1)) v(h) WHERE n > 64) SELECT cast(depth AS INT) AS depth, cast(r0 AS INT) AS r0, cast(n AS INT) AS n FROM z")
    rows = R.lineitem(s, d).groupBy("row").agg(F.count(F.lit(1)).alias("cells"))
    held = halves.join(rows, F.expr("row >= r0 AND row < r0 + n"), "left").groupBy("depth", "r0", "n").agg(F.sum("cells").alias("cells"))
    return held.select("depth", "r0", "n", F.coalesce("cells", F.lit(0).cast("long")).alias("cells"))


@query("scalar_udf_levels", with_(O.RE) + "SELECT image_id, (level // 32)::INT AS band, count(*) AS n FROM re GROUP BY 1, 2")
def _(s, d):
    @F.pandas_udf("int")
    def band(level: pd.Series) -> pd.Series:
        return (level // 32).astype("int32")

    return R.embeddings(s, d).select("image_id", band("level").alias("band")).groupBy("image_id", "band").agg(F.count(F.lit(1)).alias("n"))


@query("udaf_spread", with_(O.RE) + "SELECT image_id, (max(level) - min(level))::BIGINT AS spread FROM re GROUP BY 1")
def _(s, d):
    @F.pandas_udf("long")
    def spread(level: pd.Series) -> int:
        return int(level.max() - level.min())

    return R.embeddings(s, d).groupBy("image_id").agg(spread("level").alias("spread"))


@query("cogroup_images", with_(O.RE) + "SELECT image_id, count(*) FILTER (obj) AS objects, count(*) FILTER (NOT obj) AS others FROM re GROUP BY 1")
def _(s, d):
    px = R.embeddings(s, d)

    def both(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"image_id": [(a if len(a) else b)["image_id"].iloc[0]], "objects": [len(a)], "others": [len(b)]})

    cells = lambda want: px.filter(want).select(*KEY).groupBy("image_id")
    return cells("obj").cogroup(cells("NOT obj")).applyInPandas(both, "image_id long, objects long, others long")


@query("unpivot_counts", with_(O.RE, "c AS (SELECT image_id, count(*) FILTER (obj) AS objects, count(*) AS cells FROM re GROUP BY 1)") + "SELECT image_id, 'objects' AS measure, objects AS value FROM c UNION ALL SELECT image_id, 'cells', cells FROM c")
def _(s, d):
    wide = R.embeddings(s, d).groupBy("image_id").agg(F.count(F.when(F.col("obj"), 1)).alias("objects"), F.count(F.lit(1)).alias("cells"))
    return wide.unpivot("image_id", ["objects", "cells"], "measure", "value")


@query("approximate_columns", with_(O.RO) + "SELECT count(DISTINCT col) > 0 AND true AS near FROM ro")
def _(s, d):
    both = R.orders(s, d).agg(F.count_distinct("col").alias("exact"), F.approx_count_distinct("col", 0.02).alias("about"))
    return both.select((F.abs(F.col("about") - F.col("exact")) <= F.col("exact") * 0.1).alias("near"))


@query("sampled_cells", with_(O.RO) + "SELECT row, col FROM ro WHERE ('0x' || substr(md5(row || ':' || col), 1, 6))::BIGINT < 1677721")
def _(s, d):
    """A tenth of the cells by a hash of their place: the same cells on every run and layout."""
    return M.sampled(R.orders(s, d).select("row", "col"), 0.1)


@query("merge_zones", with_(O.RL, ZONED, _merge_round(1, "zo"), _merge_round(2, "r1")) + "SELECT 1::BIGINT AS round, node AS child, CASE WHEN p2 IS NULL THEN 1 ELSE 2 END::BIGINT AS zones FROM r1 UNION ALL SELECT 2, r2.node, sum(CASE WHEN r1.p2 IS NULL THEN 1 ELSE 2 END)::BIGINT FROM r2 JOIN r1 ON r1.node = r2.p1 OR r1.node = r2.p2 GROUP BY 1, 2")
def _(s, d):
    """How many zones a merged worker owns after the first two rounds."""
    workers = R.lineitem(s, d).groupBy(F.expr("row div 64").alias("worker_id")).agg(F.count(F.lit(1)).alias("finish"))
    plan = S.merge_plan(workers)
    one = plan.filter("round = 1").select("child", F.when(F.col("p2").isNull(), 1).otherwise(2).cast("long").alias("zones"))
    two = plan.filter("round = 2").select(F.col("child").alias("to"), F.explode(F.array_compact(F.array("p1", "p2"))).alias("child"))
    later = two.join(one, "child").groupBy(F.col("to").alias("child")).agg(F.sum("zones").alias("zones"))
    return one.select(F.lit(1).cast("long").alias("round"), "child", "zones").unionByName(later.select(F.lit(2).cast("long").alias("round"), "child", "zones"))

