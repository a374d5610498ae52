"""Mixing sources to target weights by capped water-filling.

The size of a document is its number of words. The words to mix are shared among the sources in proportion to their
weights; a source whose share would exceed ``most_epochs`` times its size is clamped there and the excess is shared
anew among the others, until no share exceeds its clamp. A share is taken as whole repetitions of the source and, for
what is left, a seeded sample: documents in the order of a keyed hash until the words are reached, the last in part.

Nothing is gathered per source in one task: words are summed by (source, hash bucket); a whole bucket lies below or
above the point where the sample ends, and only the one bucket that holds this point is put in order.

Cases: a null text has size 0 and a null source is a source of its own, the last in order; ties of the hash go by id,
then size; equal rows are mixed each; an empty table gives an empty result; sources without words get target 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import written

WORD = "[^\\x20\\x09-\\x0D]+"
#: Hexadecimal digits of the hash that name a bucket: 4,096 buckets a source.
BUCKET_DIGITS = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def cycled_weights(sources: DataFrame, weights: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """Gives the sources (one row each) the weights in turn, by code point, null last."""
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))
    return sources.withColumn("weight", F.get(F.array(*[F.lit(float(w)) for w in weights]), F.pmod(place - 1, F.lit(len(weights)))))


def water_fill(sources: DataFrame, most_epochs: int = 3, total: int | None = None) -> DataFrame:
    """Adds ``target`` to sources (source, source_size, weight). Only sums reach the driver."""
    cap = F.col("source_size") * most_epochs
    if total is None:
        total = sources.agg(F.coalesce(F.sum("source_size"), F.lit(0))).first()[0]
    clamped, level = -1, 0.0
    capped = F.lit(False)
    while True:
        count, words, weight = sources.agg(
            F.count(F.when(capped, 1)), F.coalesce(F.sum(F.when(capped, cap)), F.lit(0)), F.coalesce(F.sum(F.when(~capped, F.col("weight"))), F.lit(0.0))
        ).first()
        if count == clamped:
            break
        clamped = count
        level = float(total - words) / weight if weight > 0 else float("inf")
        capped = F.lit(level) * F.col("weight") > cap
    return sources.withColumn("target", F.when(capped, cap.cast("double")).otherwise(F.lit(level) * F.col("weight")))


def mix(docs: DataFrame, weigh=cycled_weights, most_epochs: int = 3, seed: str = "mix-1", total: int | None = None) -> DataFrame:
    """One row for each input row: doc_id, source, size, source_size, target, taken.

    ``weigh`` adds ``weight`` to the sources (source, source_size)."""
    key = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))))
    light = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", word_count(F.col("text")).alias("size"), key.alias("key"))
    light = written(light.withColumn("bucket", F.substring("key", 1, BUCKET_DIGITS)), "mix-sizes")
    buckets = written(light.groupBy("source", "bucket").agg(F.sum("size").alias("words")), "mix-buckets")
    sources = written(weigh(buckets.groupBy("source").agg(F.sum("words").alias("source_size"))), "mix-sources")
    filled = water_fill(sources, most_epochs, total)
    filled = filled.withColumn("goal", F.floor(F.col("target") + 0.5).cast("long"))
    filled = filled.withColumn("whole", F.when(F.col("source_size") > 0, F.expr("goal div source_size")).otherwise(F.lit(0)).cast("long"))
    filled = filled.withColumn("rest", F.col("goal") - F.col("whole") * F.col("source_size"))
    # The bucket of each source in which the sample ends: the first whose words reach it.
    running = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
    ends = buckets.withColumnRenamed("source", "_source").withColumn("until", F.sum("words").over(running.partitionBy("_source")))
    at = filled.join(ends, F.col("source").eqNullSafe(F.col("_source")) & (F.col("until") > F.col("rest")))
    at = at.groupBy("source", "source_size", "target", "whole", "rest").agg(F.min(F.struct("bucket", (F.col("until") - F.col("words")).alias("before"))).alias("end"))
    plan = filled.select(F.col("source").alias("_s"), "source_size", "target", "whole", "rest").join(
        at.select(F.col("source").alias("_t"), F.col("end.bucket").alias("end_bucket"), F.col("end.before").alias("before")), F.col("_s").eqNullSafe(F.col("_t")), "left"
    )
    plan = written(plan.drop("_t"), "mix-plan")
    rows = light.join(plan, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    inside = F.col("bucket") == F.col("end_bucket")
    clear = rows.filter(~F.coalesce(inside, F.lit(False))).withColumn("extra", F.when(F.col("bucket") < F.col("end_bucket"), F.col("size")).otherwise(F.lit(0)))
    order = Window.partitionBy("source").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    edge = rows.filter(inside).withColumn("upto", F.col("before") + F.sum("size").over(order))
    edge = edge.withColumn("extra", F.least(F.greatest(F.col("rest") - F.col("upto") + F.col("size"), F.lit(0)), F.col("size"))).drop("upto")
    return clear.unionByName(edge).select("doc_id", "source", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("extra")).alias("taken"))


MIX_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size, md5('mix-1:' || doc_id) AS key
  FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS words FROM d GROUP BY source),
w AS (SELECT source, words, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::DOUBLE AS weight FROM s),
o AS (SELECT *, row_number() OVER (ORDER BY 3 * words / weight, source) AS r FROM w),
p AS (
  SELECT *, ((SELECT sum(words) FROM w)::BIGINT - coalesce(sum(3 * words) OVER (ORDER BY r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT)::DOUBLE
    / sum(weight) OVER (ORDER BY r ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM o),
l AS (SELECT level FROM p WHERE level * weight <= 3 * words ORDER BY r LIMIT 1),
t AS (SELECT source, words, CASE WHEN level * weight > 3 * words THEN (3 * words)::DOUBLE ELSE level * weight END AS target FROM w, l),
g AS (SELECT source, words, target, CASE WHEN words > 0 THEN floor(target + 0.5)::BIGINT // words ELSE 0 END AS whole, floor(target + 0.5)::BIGINT AS goal FROM t),
c AS (
  SELECT doc_id, size, words, target, whole, goal - whole * words AS rest,
    sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS upto
  FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, words AS source_size, target, (whole * size + least(greatest(rest - upto + size, 0), size))::BIGINT AS taken FROM c
"""
