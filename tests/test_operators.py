"""DataFrame operators against the kernels, invariants, plans and each other."""

import io
from contextlib import redirect_stdout

import numpy as np
import pytest
from pyspark.sql import functions as F

from rastertopo import catalogue
from rastertopo.functions import kernels as K
from rastertopo.operators import distance as D
from rastertopo.operators import homotopic as H
from rastertopo.operators import layout as L
from rastertopo.operators import measures as M
from rastertopo.operators import morphology as P
from rastertopo.operators import topology as T
from rastertopo.plans import schedule as S
from rastertopo.sources import rasters as R

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def px(spark):
    return R.embeddings(spark, SF).filter("image_id < 2").cache()


def cells(df):
    return sorted(map(tuple, df.select("image_id", "row", "col").collect()))


def plan(df):
    with redirect_stdout(io.StringIO()) as out:
        df.explain("formatted")
    return out.getvalue()


def frame(spark, image, image_id=0):
    rows = [(image_id, int(r), int(c), bool(v)) for (r, c), v in np.ndenumerate(image)]
    return spark.createDataFrame(rows, "image_id long, row int, col int, obj boolean")


def test_layout_round_trips(spark, px):
    points = cells(L.sparsify(px))
    assert cells(L.sparsify(L.densify(L.sparsify(px), L.frames(px)))) == points
    assert cells(L.from_rows(L.to_rows(px)).filter("obj")) == points
    assert cells(L.from_tiles(L.to_tiles(L.sparsify(px), 32))) == points
    assert cells(L.transpose(L.transpose(px)).filter("obj")) == points


def test_edt_forms_agree(px):
    want = sorted(map(tuple, D.edt_image(px).collect()))
    for other in (D.edt_exact(px), D.edt_rows(px), D.edt_parallel(px, 3), D.edt_tiled(px, 7), D.edt_image(px, first="rows")):
        assert sorted(map(tuple, other.select("image_id", "row", "col", "d2").collect())) == want


def test_no_feature_is_null(spark):
    blank = frame(spark, np.zeros((3, 4), bool))
    assert D.edt_exact(blank).filter("d2 IS NOT NULL").isEmpty()
    assert D.edt_image(blank).filter("d2 IS NOT NULL").isEmpty()
    assert D.edt_capped(blank, 2).count() == 12
    assert P.erode(frame(spark, np.ones((3, 4), bool)), 1).count() == 12


@pytest.mark.parametrize("conn", ["8/4", "4/8"])
def test_components_by_runs_match_labels(spark, px, conn):
    n = 8 if conn == "8/4" else 4
    runs = T.components(L.sparsify(px), n)
    a = dict(runs.groupBy("image_id").agg(F.countDistinct("comp")).collect())
    b = {r.image_id: r.n_object for r in H.topology_signature(px, conn).collect()}
    assert a == b


def test_connected(spark):
    image = np.zeros((3, 5), bool)
    image[0, 0] = image[1, 1] = image[2, 2] = image[0, 4] = True
    assert T.connected(L.sparsify(frame(spark, image)), (0, 0), (2, 2), 8).first().connected
    assert not T.connected(L.sparsify(frame(spark, image)), (0, 0), (2, 2), 4).first().connected
    assert not T.connected(L.sparsify(frame(spark, image)), (0, 0), (0, 4), 8).first().connected


def test_tiles_keep_topology_for_any_side(spark):
    rng = np.random.default_rng(5)
    image = np.pad(rng.random((14, 14)) < 0.6, 2)
    want = K.signature(image)
    for side in (4, 16):
        out = H.thin_tiles(frame(spark, image), side=side)
        found = np.zeros_like(image)
        for _, r, c in cells(out):
            found[r, c] = True
        assert K.signature(found) == want
        assert not (K.simple_table("8/4")[K.masks(found)] & found)[1:-1, 1:-1].any()


def test_partitioning_does_not_matter(spark, px):
    want = cells(H.hasf(px, 2))
    assert cells(H.hasf(px.repartition(7), 2)) == want
    spark.conf.set("spark.sql.shuffle.partitions", "1")
    try:
        assert cells(H.hasf(px, 2)) == want
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")


def test_infinite_radius_stops(spark):
    image = np.zeros((9, 9), bool)
    image[2:7, 2:7] = True
    image[4, 4] = False
    out = H.smooth(frame(spark, image), float("inf"))
    assert H.topology_signature(out).first()[1:] == (1, 2)


def test_counts_of_the_order_raster(spark):
    """Pixels and signature of the 200 x 200 raster of orders, smoothed with radius 5."""
    pt = R.orders(spark, "/root/testdata/sf0.01").withColumn("obj", F.lit(True))
    after = H.hasf(pt, 5)
    assert (pt.count(), after.count()) == (12513, 6046)
    assert H.topology_signature(pt).first()[1:] == H.topology_signature(after).first()[1:] == (1789, 362)


def test_expression_plans(px, spark):
    for df, most in ((T.neighbourhood_mask(px), 1), (D.edt_capped(px, 5), 2), (T.simple_points(px), 1)):
        text = plan(df)
        assert "Python" not in text and "Arrow" not in text and "CartesianProduct" not in text and "NestedLoop" not in text
        assert text.split("Initial Plan")[-1].count("Exchange") // 2 <= most + 1
    one = plan(H.hasf(R.embeddings(spark, SF), 2))
    assert "ReadSchema: struct<vec_id:bigint,embedding:array<float>>" in one and "FlatMapGroupsInArrow" in one


def test_schedules(spark):
    tasks = spark.createDataFrame([(i, (i * 37) % 101 + 1) for i in range(53)], "task_id long, cost long")
    for plan_ in (S.balanced(tasks, 8), S.symmetric(tasks, 8), S.fair(tasks, 8), S.greedy(tasks, 8), S.greedy(tasks, 8, True)):
        assert plan_.count() == 53 and plan_.select("task_id").distinct().count() == 53
        assert {r.proc_id for r in plan_.collect()} <= set(range(8))
    assert S.bound(S.balanced(tasks, 8), 8).filter("NOT within").isEmpty()
    assert S.balanced(tasks, 8).agg(F.max("wave")).first()[0] == 6
    ratio = lambda x: S.stats(x).first().ratio_pm
    assert ratio(S.greedy(tasks, 8, True)) <= ratio(S.greedy(tasks, 8))


def test_numbering_over_stretches(spark):
    df = spark.range(0, 9000, 3).repartition(5).withColumnRenamed("id", "task_id")
    assert S.numbered(df, "task_id").filter("k * 3 <> task_id").isEmpty()


def test_merge_of_four_workers(spark):
    workers = spark.createDataFrame([(1, 10), (2, 30), (3, 20), (4, 40)], "worker_id long, finish long")
    rows = sorted(map(tuple, S.merge_plan(workers).collect()))
    assert rows == [(1, 0, 1, 3), (1, 1, 2, 4), (2, 0, 0, 1)]


def test_merge_of_nine_workers_in_three_rounds(spark):
    workers = spark.createDataFrame([(w, 10 * w + 1) for w in range(9)], "worker_id long, finish long")
    rows = sorted(S.merge_plan(workers, 3).collect(), key=lambda r: (r["round"], r.child))
    assert [tuple(r) for r in rows if r.p2 is None] == [(1, 4, 8, None), (2, 2, 4, None), (3, 1, 2, None)]
    assert [r["round"] for r in rows] == [1] * 5 + [2] * 3 + [3] * 2
    assert S.merge_plan(workers.limit(1)).isEmpty() and S.merge_plan(workers.limit(1), 3).count() == 3


def test_queues_have_two_users_at_most():
    ledger = S.QueueLedger()
    assert [ledger.queue_for(w) for w in (1, 3, 2, 4)] == [0, 0, 1, 1]
    assert ledger.push(0, (1, 1)) and not ledger.push(0, (1, 1))
    assert ledger.take(0) == [(1, 1)] and ledger.push(0, (1, 1))


def test_zone_split():
    assert S.zone_depth(512, 512, 8192) == 5 and S.zone_depth(12, 1000, 10) == 1 and S.zone_depth(8, 8, 64) == 0


def test_cache_model_by_hand(spark):
    trace = spark.createDataFrame([(i, a, "read") for i, a in enumerate([0, 64, 128, 0, 256, 0, 64])], "seq long, address long, kind string")
    # One set of two ways: lines 0 1 2 0 4 0 1 miss but for the second last access of line 0.
    assert tuple(M.cache_misses(trace, 128, 2, 64).first()) == ("read", 7, 6)
    assert M.cache_sweep(trace, [(128, 2, 64), (1024, 16, 64)]).filter("size = 1024").first().misses == 4


def test_every_sql_twin_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())
    assert len(catalogue.queries()) > 100


def test_thresholded_distance_is_the_ball(spark, px):
    inside = px.filter("row BETWEEN 3 AND 60 AND col BETWEEN 3 AND 60")
    a = {x for x in cells(P.dilate_scatter(L.sparsify(inside), 2))}
    b = set(cells(P.dilate(inside.select("image_id", "row", "col", "obj").unionByName(px.join(inside, ["image_id", "row", "col"], "left_anti").select("image_id", "row", "col", F.lit(False).alias("obj"))), 2)))
    assert b <= a


def test_warped_points_are_those_of_the_join(spark, px):
    from rastertopo.operators import layout as L

    for matrix, divisor, offset in (((2, 1, -1, 2), 6, (-9, 9)), ((1, 0, 0, -1), 2, (3, 11)), ((3, 1, 1, 2), 4, (0, -5))):
        target = px.select("image_id").distinct().selectExpr("image_id", "-2 AS row0", "0 AS col0", "30 AS n_rows", "25 AS n_cols")
        a = L.sparsify(L.warp(px, matrix, divisor, target, offset))
        b = L.warp_points(L.sparsify(px), matrix, divisor, (-2, 0, 30, 25), offset)
        assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and "Join" not in b._jdf.queryExecution().toString()


def test_stacked_images_are_filtered_as_by_themselves():
    rng = np.random.default_rng(7)
    images = [rng.random((int(rng.integers(0, 14)), 20)) < p for p in (0.3, 0.5, 0.7, 0.9) * 6]
    alone = [np.pad(x, 8) for x in images]
    for conn in ("8/4", "4/8"):
        assert H.stacked_preserved(images, 2, conn).all()
        for x in alone:
            found = K.signatures(x, np.zeros(len(x), int), 1, conn)[0]
            assert tuple(found + [0, 1]) == K.signature(x, conn)


def test_null_and_empty_texts_are_images_too(spark):
    docs = spark.createDataFrame([("a", "en"), (None, "fr"), ("", "fr"), ("x y\nz" * 90, None)], "text string, lang string")
    assert sorted(map(str, H.texts_preserved(docs, "text", 1, ["lang"]).collect())) == sorted(f"Row(lang={x!r}, preserved=True)" for x in ("en", "fr", "fr", None))


@pytest.mark.parametrize("name", ["ball_offsets", "speedup_sample", "efficiency_sample", "success_rate_tab3", "efficiency_regions", "empty_and_full_images", "time_share_sample", "efficiency_curve_sample", "recursive_halves", "scaling_of_distance"])
def test_queries_read_a_given_table(spark, name):
    from rastertopo import catalogue_more  # noqa: F401  registers its queries

    assert catalogue.queries()[name](spark, "/root/testdata/sf0.001").inputFiles()
