"""The published experiments on the given tables: ``python -m rastertopo.workloads [NAME...] [--sf DIR] [--threads 1 2 4 8]``.

Names: shares (time shares and characterised points by size and radius), distances (cost and error of the candidates),
speedups (distance, thinning and filter by threads, and the filter by scheduler), caches (miss model by scheduler and
threads), balance (scheduler balance). Each prints rows as JSON. Timings by threads start a session for each count."""

from __future__ import annotations

import argparse
import json
import subprocess
import sys
import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import kernels as K
from .operators import distance as D
from .operators import measures as M
from .operators.layout import KEY
from .plans import schedule as S
from .sources import rasters as R

GLYPH_COLUMNS = 128


def glyph_image(text: str) -> np.ndarray:
    """A text as an image of GLYPH_COLUMNS columns; a cell is object unless blank or newline."""
    cells = np.array([c not in " \n" for c in text], bool)
    rows = max(1, -(-len(cells) // GLYPH_COLUMNS))
    out = np.zeros(rows * GLYPH_COLUMNS, bool)
    out[: len(cells)] = cells
    return out.reshape(rows, GLYPH_COLUMNS)


def smooth_texts(docs: DataFrame, n: int, conn: str = "8/4", operate: str = "filter") -> DataFrame:
    """Rasterises and smooths each text within the task that reads it: doc_id, before, after (object cells), characterised.
    No pixel leaves the task."""

    def task(batches):
        import pyarrow as pa

        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                x, work = np.pad(glyph_image(text or ""), 2 * n + 2), K.Work()
                if operate == "filter":
                    y = K.hasf(x, n, conn=conn, work=work)
                elif operate == "thin":
                    d = K.capped_distance(~x, n)
                    y = K.thin(x, d == K.FAR, d, conn, None, work)
                else:
                    y = K.distance(~x, work) > 0
                out.append((doc, int(x.sum()), int(y.sum()), work.characterised))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], ["doc_id", "before", "after", "characterised"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(task, "doc_id long, before long, after long, characterised long")


def distributed(docs: DataFrame, schedule: DataFrame, processors: int) -> DataFrame:
    """The documents dealt as a schedule says: one partition for each processor, which runs its tasks to completion."""
    return docs.join(schedule.select(F.col("task_id").alias("doc_id"), "proc_id"), "doc_id").repartitionById(processors, "proc_id")


def image_of(spark: SparkSession, pt: DataFrame) -> np.ndarray:
    """One raster of bounded size (at most 512 x 512 cells) as an array, for kernels timed on one thread."""
    rows = pt.select("row", "col").toPandas()
    out = np.zeros((rows.row.max() + 1, rows.col.max() + 1), bool)
    out[rows.row, rows.col] = True
    return out


def shares(spark: SparkSession, sf: str, radii: tuple = (5, 10)) -> list[dict]:
    found = []
    for name, pt in (("200x200", R.orders(spark, sf)), ("168x288", R.events(spark, sf))):
        x = image_of(spark, pt)
        for n in radii:
            work, began = K.Work(), time.perf_counter()
            K.hasf(np.pad(x, 2 * n + 2), n, work=work)
            total = time.perf_counter() - began
            found.append({"size": name, "radius": n, "characterised": work.characterised, "changed": work.changed} | {f"{k}_share": round(v / total, 4) for k, v in work.seconds.items()})
    return found


def distances(spark: SparkSession, sf: str) -> list[dict]:
    pt = R.orders(spark, sf)
    box = pt.agg(F.max("row").alias("r"), F.max("col").alias("c")).first()
    cells = spark.range(box.r + 1).select(F.lit(0).cast("long").alias("image_id"), F.col("id").cast("int").alias("row"), F.explode(F.sequence(F.lit(0), F.lit(box.c))).alias("col"))
    px = cells.join(pt.select(*KEY, F.lit(True).alias("obj")), KEY, "left").withColumn("obj", F.coalesce("obj", F.lit(False)))
    variants = ["exact", "scan4", "scan3x3", "prop4", "prop8", "prop_exact"]
    cost = {r.variant: r.asDict() for r in D.edt_work(px, variants).collect()}
    return [cost.get(r.variant, {}) | r.asDict() for r in D.edt_errors(px, variants).collect()]


def caches(spark: SparkSession, sf: str, threads: tuple = (1, 2, 4, 8)) -> list[dict]:
    pt, found = R.lineitem(spark, sf).select(*KEY), []
    tasks = spark.range(64).select(F.col("id").alias("task_id"), F.lit(1).cast("long").alias("cost"))
    for t in threads:
        for name, plan in (("balanced", S.balanced), ("symmetric", S.symmetric)):
            for r in M.cache_misses(M.band_trace(pt, plan(tasks, t), 8, 512), 32768, 8, 64).collect():
                found.append({"threads": t, "scheduler": name} | r.asDict())
    return found


def balance(spark: SparkSession, sf: str) -> list[dict]:
    tasks = R.table(spark, sf, "documents").select(F.col("doc_id").alias("task_id"), F.length("text").cast("long").alias("cost"))
    plans = {"symmetric": S.symmetric(tasks, 8), "round_robin": S.balanced(tasks, 8), "fair": S.fair(tasks, 8), "next_free": S.greedy(tasks, 8), "largest_first": S.greedy(tasks, 8, True)}
    return [{"scheduler": name} | S.stats(plan).first().asDict() for name, plan in plans.items()]


def timed(action, best_of: int) -> float:
    times = []
    for _ in range(best_of):
        began = time.perf_counter()
        action().write.format("noop").mode("overwrite").save()
        times.append(time.perf_counter() - began)
    return round(min(times), 3)


def one_speed(sf: str, threads: int) -> dict:
    """Times with one number of threads, in a session of its own: best of 3 (distance), best of 2 (the others)."""
    spark = (
        SparkSession.builder.master(f"local[{threads}]").config("spark.sql.shuffle.partitions", threads).config("spark.ui.enabled", "false").config("spark.driver.memory", "4g")
        .config("spark.sql.adaptive.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    docs = R.table(spark, sf, "documents").select("doc_id", "text").cache()
    tasks = docs.select(F.col("doc_id").alias("task_id"), F.length("text").cast("long").alias("cost"))
    even = distributed(docs, S.balanced(tasks, threads), threads).cache()
    blocks = distributed(docs, S.symmetric(tasks, threads), threads).cache()
    even.count(), blocks.count(), timed(lambda: smooth_texts(even.limit(threads), 1), 1)
    out = {"threads": threads, "distance": timed(lambda: smooth_texts(even, 2, operate="distance"), 3), "thinning": timed(lambda: smooth_texts(even, 2, operate="thin"), 2)}
    out |= {"filter_balanced": timed(lambda: smooth_texts(even, 2), 2), "filter_symmetric": timed(lambda: smooth_texts(blocks, 2), 2)}
    spark.stop()
    return out


def speedups(sf: str, threads: tuple = (1, 2, 4, 8)) -> list[dict]:
    rows = []
    for t in threads:
        run = subprocess.run([sys.executable, "-m", "rastertopo.workloads", "--one", str(t), "--sf", sf], capture_output=True, text=True, check=True)
        rows.append(json.loads(run.stdout.strip().splitlines()[-1]))
    for r in rows:
        for k in ("distance", "thinning", "filter_balanced", "filter_symmetric"):
            r[f"{k}_speedup"] = round(rows[0][k] / r[k], 2)
            r[f"{k}_efficiency"] = round(rows[0][k] / r[k] / r["threads"], 3)
    return rows


def main() -> None:
    parser = argparse.ArgumentParser()
    parser.add_argument("names", nargs="*", default=[])
    parser.add_argument("--sf", default="/root/testdata/sf0.01")
    parser.add_argument("--threads", nargs="*", type=int, default=[1, 2, 4, 8])
    parser.add_argument("--one", type=int)
    args = parser.parse_args()
    if args.one:
        print(json.dumps(one_speed(args.sf, args.one)))
        return
    names = args.names or ["shares", "distances", "balance", "caches", "speedups"]
    if "speedups" in names:
        for row in speedups(args.sf, tuple(args.threads)):
            print(json.dumps({"experiment": "speedups"} | row), flush=True)
    rest = [n for n in names if n != "speedups"]
    if rest:
        spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "4g").getOrCreate()
        spark.sparkContext.setLogLevel("ERROR")
        for name in rest:
            for row in globals()[name](spark, args.sf):
                print(json.dumps({"experiment": name} | row, default=float), flush=True)


if __name__ == "__main__":
    main()
