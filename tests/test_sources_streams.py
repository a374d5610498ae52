"""Files, streams, the SQL surface and the planner."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rastertopo.functions import sql
from rastertopo.operators import homotopic as H
from rastertopo.plans import planner
from rastertopo.sources import netpbm as N
from rastertopo.sources import rasters as R
from rastertopo.streaming import events as E

SF = "/root/testdata/sf0.001"


def test_netpbm_formats():
    bits = np.random.default_rng(1).integers(0, 2, (5, 11)).astype(np.int32)
    gray = np.random.default_rng(2).integers(0, 700, (4, 3)).astype(np.int32)
    assert (N.parse(N.encode(bits)) == bits).all() and (N.parse(N.encode(gray, True)) == gray).all() and (N.parse(N.encode(gray % 256, True)) == gray % 256).all()
    assert N.parse(b"P1\n# c\n3 2\n1 0 1\n010").tolist() == [[1, 0, 1], [0, 1, 0]]
    assert N.parse(b"P2 2 2 9\n1 2\n# x\n3 4").tolist() == [[1, 2], [3, 4]]
    with pytest.raises(ValueError):
        N.parse(b"P6 1 1")


def test_netpbm_source(spark, tmp_path):
    folder = tmp_path / "images"
    folder.mkdir()
    px = R.embeddings(spark, SF).filter("image_id < 2")
    for r in N.images(px).collect():
        (folder / f"{r.image_id}.pbm").write_bytes(bytes(r.content))
    want = sorted(map(tuple, px.filter("obj").select("image_id", "row", "col").collect()))
    N.register(spark)
    got = spark.read.format("netpbm").load(str(folder))
    assert sorted(map(tuple, got.filter("obj").select("image_id", "row", "col").collect())) == want
    assert N.read(spark, str(folder)).filter("obj").count() == len(want)
    out = spark.readStream.format("netpbm").load(str(folder)).writeStream.format("memory").queryName("netpbm_rows").option("checkpointLocation", str(tmp_path / "c")).start()
    try:
        out.processAllAvailable()
        assert spark.table("netpbm_rows").filter("obj").count() == len(want)
    finally:
        out.stop()


def test_streams_equal_batches(spark):
    ev = R.table(spark, SF, "events")
    assert E.replay(spark, SF, E.day_cells, ["n"]).agg(F.sum("n")).first()[0] == ev.count()
    assert E.replay(spark, SF, E.sliding_cells, ["n"]).agg(F.sum("n")).first()[0] == 24 * ev.count()


def test_micro_batches_are_smoothed(spark, tmp_path):
    px = R.embeddings(spark, SF).filter("image_id = 0").select("image_id", "row", "col", "obj")
    px.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(px.schema).parquet(str(tmp_path / "in"))
    E.smooth_batches(stream, 1, str(tmp_path / "out"), str(tmp_path / "checkpoint")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).select("image_id", "row", "col")
    assert got.exceptAll(H.hasf(px, 1)).isEmpty() and got.count() == H.hasf(px, 1).count()


def test_sql_surface(spark):
    px = R.embeddings(spark, SF).filter("image_id = 1")
    sql.register(spark, px)
    got = spark.sql("SELECT * FROM homotopic_smooth(TABLE(SELECT image_id, row, col, obj, 2 AS radius FROM pixels) PARTITION BY image_id)")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, H.hasf(px, 2).collect()))


def test_planner(spark):
    px = R.embeddings(spark, SF)
    size = planner.sizes(px)
    assert (size.images, size.largest) == (8, 4096)
    assert planner.distance_plan(size) == "image" and planner.distance_plan(size, 3) == "capped"
    assert planner.distance_plan(planner.Sizes(1, 10**9, 10**5)) == "tiled" and len(planner.filter_steps(3)) == 12
    assert planner.distance(px, radius=2, size=size).filter("d2 > 4").isEmpty()
