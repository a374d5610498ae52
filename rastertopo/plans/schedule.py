"""Split, distribute, merge: zones, schedulers, their measures, and the plan that merges workers pairwise."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Stretches that an order is cut into; their bounds and counts are what reaches the driver.
STRETCHES = 256


def numbered(df: DataFrame, key: str, name: str = "k") -> DataFrame:
    """Adds the 0-based rank by a unique integer key, without bringing all rows to one task."""
    n = df.count()
    cuts = [i / STRETCHES for i in range(1, STRETCHES)] if n > 10 * STRETCHES else []
    bounds = sorted(set(df.agg(F.percentile_approx(key, cuts, 10 * STRETCHES)).first()[0])) if cuts else []
    stretch = F.size(F.filter(F.array(*[F.lit(b) for b in bounds]), lambda b: b < F.col(key))) if bounds else F.lit(0)
    counts = dict(df.groupBy(stretch.alias("s")).count().collect()) if bounds else {}
    before = dict(zip(range(len(bounds) + 1), accumulate([0] + [counts.get(s, 0) for s in range(len(bounds))])))
    offset = F.create_map(*[F.lit(x) for s, b in before.items() for x in (s, b)])[F.col("_s")] if bounds else F.lit(0)
    rank = F.row_number().over(Window.partitionBy("_s").orderBy(key)) - 1
    return df.withColumn("_s", stretch).withColumn(name, (rank + offset).cast("long")).drop("_s")


def zone_depth(n_rows: int, n_cols: int, max_pixels: int, min_rows: int = 6) -> int:
    """How often a frame is halved by rows until its zones are small enough, none with fewer than ``min_rows`` rows."""
    depth = 0
    while n_rows * n_cols > max_pixels << depth and n_rows >> (depth + 1) >= min_rows:
        depth += 1
    return depth


def zones(pt: DataFrame, n_rows: int, n_cols: int, max_pixels: int, min_rows: int = 6, row0: int = 0) -> DataFrame:
    """Adds zone and half (of the zone's rows) by recursive halving: a computed key, no shuffle."""
    parts = 1 << zone_depth(n_rows, n_cols, max_pixels, min_rows)
    at = (F.col("row") - row0).cast("long")
    zone = F.floor(at * parts / n_rows).cast("int")
    return pt.withColumn("zone", zone).withColumn("half", F.pmod(F.floor(at * parts * 2 / n_rows), F.lit(2)).cast("int"))


def stride(column: str, workers: int) -> Column:
    return F.pmod(F.col(column), F.lit(workers))


def balanced(tasks: DataFrame, processors: int) -> DataFrame:
    """Run to completion in waves: each free processor gets one task; what is left waits for the next wave."""
    k = F.col("k")
    return numbered(tasks, "task_id").select("task_id", "cost", F.pmod(k, F.lit(processors)).cast("int").alias("proc_id"), F.floor(k / processors).cast("long").alias("wave"))


def symmetric(tasks: DataFrame, processors: int) -> DataFrame:
    """The baseline: contiguous blocks of equally many tasks, whatever their cost."""
    n = tasks.count()
    q, r = divmod(n, processors)
    k = F.col("k")
    block = F.when(k < r * (q + 1), F.floor(k / (q + 1))).otherwise(r + F.floor((k - r * (q + 1)) / max(q, 1))).cast("int")
    first = F.when(F.col("proc_id") <= r, F.col("proc_id") * (q + 1)).otherwise(r * (q + 1) + (F.col("proc_id") - r) * q)
    return numbered(tasks, "task_id").withColumn("proc_id", block).select("task_id", "cost", "proc_id", (k - first).cast("long").alias("wave"))


def clocked(tasks: DataFrame, processors: int, ticks: int) -> DataFrame:
    """Clock-driven: the processors take turns by slices of ``ticks`` tasks, whatever their cost."""
    return numbered(tasks, "task_id").select("task_id", "cost", F.pmod(F.floor(F.col("k") / ticks), F.lit(processors)).cast("int").alias("proc_id"))


def staircase(tasks: DataFrame, processors: int) -> DataFrame:
    """A rotating staircase: waves go through the processors forth and back, so no processor is always first."""
    at, back = F.pmod("k", F.lit(processors)), F.pmod(F.floor(F.col("k") / processors), F.lit(2)) == 1
    return numbered(tasks, "task_id").select("task_id", "cost", F.when(back, processors - 1 - at).otherwise(at).cast("int").alias("proc_id"))


def by_priority(tasks: DataFrame, processors: int) -> DataFrame:
    """Waves by falling priority, ties by task: a higher priority goes first within its class."""
    order = Window.partitionBy("priority").orderBy("task_id")
    counts = tasks.groupBy("priority").count()
    above = counts.select("priority", F.coalesce(F.sum("count").over(Window.orderBy(F.col("priority").desc()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    k = F.col("before") + F.row_number().over(order) - 1
    ranked = tasks.join(above, "priority").withColumn("k", k)
    return ranked.select("task_id", "cost", "priority", F.pmod("k", F.lit(processors)).cast("int").alias("proc_id"), F.floor(F.col("k") / processors).cast("long").alias("wave"))


def fair(tasks: DataFrame, processors: int) -> DataFrame:
    """Contiguous blocks of about equal cost: a task goes where its running cost falls."""
    total = tasks.agg(F.sum("cost")).first()[0] or 1
    running = F.sum("cost").over(Window.orderBy("task_id").rowsBetween(Window.unboundedPreceding, 0)) - F.col("cost")
    return tasks.withColumn("_c", running).select("task_id", "cost", F.floor(F.col("_c") * processors / F.lit(total)).cast("int").alias("proc_id"))


def greedy(tasks: DataFrame, processors: int, largest_first: bool = False) -> DataFrame:
    """The next task goes to the processor that is free first; ``largest_first`` sorts by falling cost. One heap over
    (task, cost) pairs, in one task: meant for schedules of up to some million tasks."""

    def task(table):
        import heapq

        import pyarrow as pa

        rows = sorted(zip(table.column("task_id").to_pylist(), table.column("cost").to_pylist()), key=(lambda x: (-x[1], x[0])) if largest_first else (lambda x: x[0]))
        heap, waves, out = [(0, p) for p in range(processors)], [0] * processors, []
        for t, cost in rows:
            free, p = heapq.heappop(heap)
            out.append((t, cost, p, waves[p]))
            waves[p] += 1
            heapq.heappush(heap, (free + cost, p))
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * 4, (pa.int64(), pa.int64(), pa.int32(), pa.int64()))], names=["task_id", "cost", "proc_id", "wave"])

    return tasks.select("task_id", F.col("cost").cast("long").alias("cost")).groupBy(F.lit(0).alias("_")).applyInArrow(task, "task_id long, cost long, proc_id int, wave long")


def loads(schedule: DataFrame) -> DataFrame:
    return schedule.groupBy("proc_id").agg(F.count(F.lit(1)).alias("n"), F.sum("cost").cast("long").alias("cost"))


def stats(schedule: DataFrame) -> DataFrame:
    """max_cost (the makespan), total, ratio_pm (greatest over mean, per mille) and idle_pm of a schedule."""
    a = loads(schedule).agg(F.max("cost").alias("max_cost"), F.sum("cost").alias("total"), F.count(F.lit(1)).alias("procs"), F.max("n").alias("max_tasks"))
    return a.select("max_cost", "total", "max_tasks", F.expr("max_cost * procs * 1000 div total").alias("ratio_pm"), F.expr("(max_cost * procs - total) * 1000 div (max_cost * procs)").alias("idle_pm"))


def bound(schedule: DataFrame, processors: int) -> DataFrame:
    """proc_id, n, limit, within: no processor gets more than ceil(tasks / processors) tasks."""
    total = schedule.agg(F.count(F.lit(1)).alias("_t"))
    limit = F.expr(f"(_t + {processors - 1}) div {processors}")
    return loads(schedule).crossJoin(F.broadcast(total)).select("proc_id", "n", limit.alias("limit"), (F.col("n") <= limit).alias("within"))


def merge_plan(workers: DataFrame, rounds: int | None = None) -> DataFrame:
    """round, child, p1, p2: workers (worker_id, finish) pair up as they finish; a child goes on with the later one's time
    and is named by its place in its round; of an odd number the last goes on alone (p2 null). One row a worker: small.
    It goes on until one is left, or for just so many ``rounds``, in which one that is left goes on alone."""
    order = Window.orderBy("finish", "node")
    level = workers.select(F.col("worker_id").cast("long").alias("node"), F.col("finish").cast("long").alias("finish"))
    n, number = workers.count(), 0
    done = level.select(F.lit(0).cast("long").alias("round"), F.col("node").alias("child"), F.col("node").alias("p1"), F.col("node").alias("p2")).limit(0) if n <= 1 and not rounds else None
    while n > 1 if rounds is None else number < rounds:
        number += 1
        placed = level.withColumn("k", F.row_number().over(order) - 1)
        pairs = placed.groupBy(F.floor(F.col("k") / 2).alias("child")).agg(F.min(F.struct("k", "node")).alias("a"), F.max(F.struct("k", "node")).alias("b"), F.max("finish").alias("finish"))
        merged = pairs.select(F.lit(number).cast("long").alias("round"), "child", F.col("a.node").alias("p1"), F.when(F.col("a.k") != F.col("b.k"), F.col("b.node")).alias("p2"))
        done = merged if done is None else done.unionByName(merged)
        level = pairs.select(F.col("child").alias("node"), "finish")
        n = (n + 1) // 2
    return done


class QueueLedger:
    """Shared queues between workers: one is made on demand, has two users at most, and is available while it has one.
    A pixel is queued once until it is taken."""

    def __init__(self):
        self.users: dict[int, list[int]] = {}
        self.held: dict[int, dict] = {}

    def queue_for(self, worker: int) -> int:
        """The queue that a finishing worker shares: an available one of another worker, or a new one."""
        for q, users in self.users.items():
            if len(users) == 1 and users[0] != worker:
                users.append(worker)
                return q
        q = len(self.users)
        self.users[q], self.held[q] = [worker], {}
        return q

    def push(self, queue: int, pixel) -> bool:
        fresh = pixel not in self.held[queue]
        self.held[queue][pixel] = None
        return fresh

    def take(self, queue: int) -> list:
        out = list(self.held[queue])
        self.held[queue] = {}
        return out
