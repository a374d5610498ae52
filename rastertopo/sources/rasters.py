"""Rasters derived from the given tables, in integer arithmetic so that any engine gets the same cells.

PIXELS: image_id, row, col, obj, level. POINTS: image_id, row, col (object cells only)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bucket(value: Column, cells: int, span: int) -> Column:
    """floor(value * cells / span) of an integer column."""
    return F.floor(value.cast("long") * cells / F.lit(span)).cast("int")


def rasterize(df: DataFrame, image: Column, row: Column, col: Column, threshold: int = 1) -> DataFrame:
    """Any table to POINTS with a count ``n``: the cells that hold at least ``threshold`` rows (combined before the shuffle)."""
    cells = df.select(image.cast("long").alias("image_id"), row.cast("int").alias("row"), col.cast("int").alias("col"))
    return cells.groupBy("image_id", "row", "col").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= threshold)


def cents(column: str) -> Column:
    return F.round(F.col(column) * 100).cast("long")


def embeddings_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RE in the row layout: image_id, row, vals (the 64 values of a vector)."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.expr("vec_id div 64").alias("image_id"), F.pmod("vec_id", F.lit(64)).cast("int").alias("row"), F.col("embedding").alias("vals"))


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RE: the signs of the vectors, 64 to an image; level is the value on 0..255."""
    cells = embeddings_rows(spark, sf_dir).select("image_id", "row", F.posexplode("vals").alias("col", "value"))
    level = F.least(F.greatest(F.floor((F.col("value").cast("double") + 1) * 127.5), F.lit(0)), F.lit(255)).cast("int")
    return cells.select("image_id", "row", "col", (F.col("value") > 0).alias("obj"), level.alias("level"))


def orders(spark: SparkSession, sf_dir: str, threshold: int = 1) -> DataFrame:
    """RO: price by date, 200 x 200."""
    day = F.datediff("o_orderdate", F.lit("1995-01-01"))
    return rasterize(table(spark, sf_dir, "orders"), F.lit(0), bucket(cents("o_totalprice"), 200, 50_000_000), bucket(day, 200, 2405), threshold)


def events(spark: SparkSession, sf_dir: str, threshold: int = 1) -> DataFrame:
    """RV: user modulo 168 by five-minute slot of the day, 168 x 288."""
    slot = F.expr("(hour(ts) * 60 + minute(ts)) div 5")
    return rasterize(table(spark, sf_dir, "events"), F.lit(0), F.pmod("user_id", F.lit(168)), slot, threshold)


def lineitem(spark: SparkSession, sf_dir: str, threshold: int = 1) -> DataFrame:
    """RL: extended price by ship date, 512 x 512."""
    day = F.datediff("l_shipdate", F.lit("1995-01-02"))
    return rasterize(table(spark, sf_dir, "lineitem"), F.lit(0), bucket(cents("l_extendedprice"), 512, 10_500_000), bucket(day, 512, 2499), threshold)


def glyphs(df: DataFrame, id_col: str, text_col: str, width: int = 128) -> DataFrame:
    """RD, RB: a text as an image of ``width`` columns; a cell is object unless blank or newline."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    chars = F.split(text, "")
    cells = df.select(F.col(id_col).cast("long").alias("image_id"), F.posexplode(F.filter(chars, lambda c: c != "")).alias("p", "c"))
    return cells.select("image_id", F.expr(f"p div {width}").cast("int").alias("row"), F.expr(f"p % {width}").cast("int").alias("col"), (~F.col("c").isin(" ", "\n")).alias("obj"), F.pmod(F.expr("ascii(c)"), F.lit(256)).alias("level"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return glyphs(table(spark, sf_dir, "documents"), "doc_id", "text")


def markup_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """RP by image: cells, and object cells (characters inside tags)."""
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("image_id"), F.coalesce("html", F.lit("")).alias("html"))
    tagged = F.length("html") - F.length(F.regexp_replace("html", "<[^>]*>", ""))
    return p.select("image_id", F.length("html").cast("long").alias("cells"), tagged.cast("long").alias("objects"))


def shapes(spark: SparkSession, rows: int, cols: int, kind: str = "rings", seed: int = 1, image_id: int = 0) -> DataFrame:
    """RS: synthetic images without a file: rectangles, bars, rings, checkers or salt noise."""
    cells = spark.range(rows).select(F.col("id").cast("int").alias("row"), F.explode(F.sequence(F.lit(0), F.lit(cols - 1))).alias("col"))
    r, c = F.col("row"), F.col("col")
    edge = F.least(r, c, F.lit(rows - 1) - r, F.lit(cols - 1) - c)
    obj = {
        "rings": F.pmod(F.expr(f"(least(row, col, {rows - 1} - row, {cols - 1} - col)) div 2"), F.lit(2)) == 1,
        "rectangles": (edge >= 2) & (edge < 6),
        "bars": F.pmod(F.expr("col div 3"), F.lit(2)) == 0,
        "checkers": F.pmod(r + c, F.lit(2)) == 0,
        "salt": F.pmod(F.xxhash64(F.lit(seed), r, c), F.lit(100)) < 30,
    }[kind]
    return cells.select(F.lit(image_id).cast("long").alias("image_id"), "row", "col", obj.alias("obj"), F.lit(None).cast("int").alias("level"))
