"""Bands of one image over many tasks, the generic loop, distances of long gaps, state in streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rastertopo.functions import generic, gray
from rastertopo.functions import kernels as K
from rastertopo.operators import measures as M
from rastertopo.operators import zones as Z
from rastertopo.streaming import stateful


def pixels(spark, x, image=0):
    rows = [(image, int(r), int(c), bool(x[r, c])) for r in range(x.shape[0]) for c in range(x.shape[1])]
    return spark.createDataFrame(rows, "image_id long, row int, col int, obj boolean")


def random_image(seed, shape=(23, 31), share=0.6):
    return np.random.default_rng(seed).random(shape) < share


def as_array(df, shape, margin):
    out = np.zeros((shape[0] + 2 * margin, shape[1] + 2 * margin), bool)
    for r in df.collect():
        out[r.row + margin, r.col + margin] = True
    return out


@pytest.mark.parametrize("rows,processors,plan", [(5, 3, "symmetric")])
def test_filter_by_bands_keeps_the_topology(spark, rows, processors, plan):
    x = random_image(rows)
    out = as_array(Z.hasf(pixels(spark, x), 1, rows=rows, processors=processors, plan=plan), x.shape, 4)
    wide = np.pad(x, 4)
    assert K.signature(out) == K.signature(wide)
    # What the filter may change lies within its radius: no cell far from the image's border of object and background.
    assert not (out & (K.capped_distance(wide, 2) == K.FAR)).any()


def test_thinning_by_bands(spark):
    """One band is the canonical thinning of the frame that it stands in; several keep its topology."""
    x = np.pad(random_image(9, (12, 14)), ((2, 2), (1, 1)))
    d = K.capped_distance(~x, 2)
    whole = K.thin(x, d == K.FAR, d)
    x, whole = x[2:-2, 1:-1], whole[2:-2, 1:-1]
    assert (as_array(Z.thin(pixels(spark, x), rows=64), x.shape, 0) == whole).all()
    parts = as_array(Z.thin(pixels(spark, x), rows=3, processors=2), x.shape, 0)
    assert K.signature(parts) == K.signature(x)


def test_constraints_hold_in_bands(spark):
    x = random_image(4, (14, 15))
    px = pixels(spark, x)
    c, d = px.filter("obj AND (row + col) % 3 = 0"), px.filter("NOT obj AND (row + col) % 3 = 0")
    out = Z.hasf(px, 1, c, d)
    assert c.join(out, ["image_id", "row", "col"], "left_anti").isEmpty() and d.join(out, ["image_id", "row", "col"], "left_semi").isEmpty()


@pytest.mark.parametrize("conn", ["8/4", "4/8"])
def test_generic_loop(conn):
    for seed in range(6):
        x = random_image(seed, (15, 17))
        canonical = K.thin(x, None, K.distance(~np.pad(x, 1))[1:-1, 1:-1], conn)
        assert (generic.skeleton(x, conn) == canonical).all()
        four = generic.skeleton(x, conn, recheck=4)
        assert K.signature(np.pad(four, 1), conn) == K.signature(np.pad(x, 1), conn)
        f = np.random.default_rng(seed).integers(0, 4, (9, 11))
        kernel = generic.gray_kernel(f, conn)
        whole = gray.gray_kernel(f, conn)[0]
        for k in range(1, 4):
            assert K.signature(kernel >= k, conn) == K.signature(whole >= k, conn) == K.signature(f >= k, conn)


def test_long_gaps_are_exact():
    gaps = np.array([600_000, K.FAR, 5])
    assert K.lower_envelope(gaps).tolist() == [29, 26, 25]
    assert K.lower_envelope(np.array([600_000])).tolist() == [360_000_000_000]


def test_measures_of_runs(spark):
    runs = spark.createDataFrame([("f", t, 1, 1000.0 / t if t % 2 == 0 or t == 1 else 900.0 / t * 1.5) for t in (1, 2, 3, 4)], "variant string, threads int, rep int, ms double")
    assert [r.threads for r in M.efficiency_curve(runs).filter("dip").collect()] == [3]
    sizes = spark.createDataFrame([(10, 30), (100, 3000), (1000, 300000)], "n long, work long")
    assert M.scaling(sizes).first().exponent == pytest.approx(2.0)


def test_tile_state_over_batches(spark, tmp_path):
    x = random_image(2, (8, 8))
    px = pixels(spark, x)
    folder = str(tmp_path / "in")
    px.filter("row < 4").coalesce(1).write.mode("append").parquet(folder)
    px.filter("row >= 4").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(px.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = sorted(stateful.rows_of(spark, stateful.tile_filter(stream, 8, 1), "update").collect())
    assert [r.version for r in got] == [1, 2] and got[-1].n_before == int(x.sum())


def test_merge_by_finish(spark, tmp_path):
    workers = spark.createDataFrame([(0, w, f) for w, f in ((1, 4), (2, 1), (3, 3), (4, 2), (5, 9))], "image_id long, worker_id long, finish long")
    workers.coalesce(1).write.parquet(str(tmp_path / "w"))
    stream = spark.readStream.schema(workers.schema).parquet(str(tmp_path / "w"))
    got = stateful.rows_of(spark, stateful.finish_merge(stream), "append").orderBy("round", "child").collect()
    assert [tuple(r) for r in got] == [(0, 1, 0, 2, 4), (0, 1, 1, 3, 1), (0, 2, 0, 0, 1)]


def test_a_worker_that_no_other_met_goes_on_alone(spark):
    schema = "image_id long, round int, child int, p1 long, p2 long"
    pairs = spark.createDataFrame([(0, 1, 0, 1, 2), (0, 1, 1, 3, 4), (0, 1, 2, 5, 6), (0, 2, 0, 0, 1), (1, 1, 0, 1, 2), (1, 1, 1, 3, 4), (1, 2, 0, 0, 1)], schema)
    workers = spark.createDataFrame([(i, w) for i, n in ((0, 7), (1, 5), (2, 1)) for w in range(1, n + 1)], "image_id long, worker_id long")
    got = stateful.left_alone(pairs, workers).orderBy("image_id", "round").collect()
    assert [tuple(r) for r in got] == [(0, 1, 3, 7, None), (0, 2, 1, 2, 3), (0, 3, 0, 0, 1), (1, 1, 2, 5, None), (2, 1, 0, 1, None)]


def test_sample_is_the_same_everywhere(spark):
    cells = spark.range(2000).select((F.col("id") % 50).cast("int").alias("row"), (F.col("id") / 50).cast("int").alias("col"))
    a, b = M.sampled(cells, 0.2), M.sampled(cells.repartition(7), 0.2)
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and 300 < a.count() < 500


def test_complete_output_stays_off_the_driver_and_once(spark, tmp_path):
    rows = spark.range(40).selectExpr("id % 3 AS k")
    rows.repartition(4).write.parquet(str(tmp_path / "in"))
    streamed = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).groupBy("k").count()
    got = stateful.rows_of(spark, streamed, "complete")
    assert sorted(map(tuple, got.collect())) == [(0, 14), (1, 13), (2, 13)] and got.inputFiles()
