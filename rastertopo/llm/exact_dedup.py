"""Exact dedup with a log-structured merge index of text digests, in DataFrame operations only.

Each task of the scan is a memtable: it digests its texts and flushes them, sorted by digest, as Parquet files of at
most ``MEMTABLE_ROWS`` rows, with row-group statistics and a Bloom filter on the digest. A level takes ``FANOUT`` flushes
or merged runs; a full level is merged into one run of the next, so a row is rewritten once a level and not once a
flush. Compaction merges what the levels hold into one run that keeps, for each digest, the first identifier and the
number of rows. A look-up asks the runs for one digest, which statistics and filters answer for most files. Texts that
hit a digest held by several rows are compared byte by byte; where a digest is shared by different texts, these are
told apart by their bytes.

Cases: a null text counts as empty; equal rows count as copies, a repeated doc_id is a row of its own, and of rows equal
in doc_id and text one alone stays; a null id stays only where all ids of a text are null; an empty table gives an empty
result; columns other than the id and the text are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import KeyFilter, scratch_path, text_or_empty, written

MEMTABLE_ROWS, FANOUT = 1 << 20, 8
#: Writer options of a run: a bound of its files, and the filter that look-ups use before they read a row group.
RUN_OPTIONS = {"maxRecordsPerFile": str(MEMTABLE_ROWS), "parquet.bloom.filter.enabled#digest": "true", "parquet.bloom.filter.expected.ndv#digest": "200000"}
RUN = "digest binary, id long, place long, n long"


class DigestIndex:
    """A merge index over digests. ``keep`` says which row of equal texts stays: "smallest" or "largest" id.

    ``place`` numbers the rows of a flush, so that one of several equal rows is the first. ``digest_bytes`` shortens the
    SHA-256 digests that the index is keyed by: a weak digest only costs time, as bytes decide."""

    def __init__(self, spark: SparkSession, keep: str = "smallest", digest_bytes: int = 32, fanout: int = FANOUT):
        if keep not in ("smallest", "largest"):
            raise ValueError("keep is smallest or largest")
        self.spark, self.keep, self.digest_bytes, self.fanout = spark, keep, digest_bytes, fanout
        self.log: list[str] = []
        self.levels: list[list[str]] = [[]]
        self.flushed = 0

    def key(self, sha: Column) -> Column:
        return sha if self.digest_bytes >= 32 else F.substring(sha, 1, self.digest_bytes)

    def first(self) -> Column:
        """Of the rows (id, place): the one that stays."""
        if self.keep == "largest":
            best = F.max(F.struct("id", (-F.col("place")).alias("back")))
            return F.struct(best["id"].alias("id"), (-best["back"]).alias("place"))
        best = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "place"))
        return F.struct(best["id"].alias("id"), best["place"].alias("place"))

    def flush(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> None:
        """Adds rows: sorted runs of each task that holds some of them. No shuffle."""
        path = scratch_path(self.spark, "digest-runs")
        run = docs.select(F.col(id_col).cast("long").alias("id"), F.unhex(F.sha2(text_or_empty(text_col), 256)).alias("sha"))
        # The lower 33 bits number the rows of a task and the next ones the task, so flushes get bits of their own.
        place = F.monotonically_increasing_id().bitwiseXOR(F.lit(self.flushed << 56))
        run = run.select(self.key(F.col("sha")).alias("digest"), "id", place.alias("place"), F.lit(1).cast("long").alias("n"), "sha")
        run.sortWithinPartitions("digest").write.options(**RUN_OPTIONS).parquet(path)
        self.flushed += 1
        self.log.append(path)
        self.levels[0].append(path)
        level = 0
        while len(self.levels[level]) >= self.fanout:
            if level + 1 == len(self.levels):
                self.levels.append([])
            self.levels[level + 1].append(self.merge(self.levels[level]))
            self.levels[level] = []
            level += 1

    def merge(self, paths: list[str]) -> str:
        """One run of several: for each digest the row that stays and the number of rows (combined before the shuffle)."""
        path = scratch_path(self.spark, "digest-level")
        merged = self.spark.read.schema(RUN).parquet(*paths).groupBy("digest").agg(self.first().alias("best"), F.sum("n").alias("n"))
        merged.select("digest", "best.id", "best.place", "n").sortWithinPartitions("digest").write.options(**RUN_OPTIONS).parquet(path)
        return path

    def entries(self) -> DataFrame:
        return self.spark.read.schema(RUN + ", sha binary").parquet(*self.log)

    def compact(self) -> DataFrame:
        """Merges all runs into one: digest, keep_id, keep_place, group_size."""
        runs = [path for level in self.levels for path in level]
        if len(runs) > 1 or self.levels[0]:
            self.levels = [[], *[[] for _ in self.levels[1:-1]], [self.merge(runs)]]
        top = self.spark.read.schema(RUN).parquet(*self.levels[-1])
        return top.select("digest", F.col("id").alias("keep_id"), F.col("place").alias("keep_place"), F.col("n").alias("group_size"))

    def find(self, digest: bytes) -> DataFrame:
        """The entry of one digest: the runs' statistics and filters leave most files unread."""
        runs = [path for level in self.levels for path in level]
        held = self.spark.read.schema(RUN).parquet(*runs).filter(F.col("digest") == F.lit(bytearray(digest[: self.digest_bytes])))
        return held.groupBy("digest").agg(self.first().alias("best"), F.sum("n").alias("group_size")).select("digest", F.col("best.id").alias("keep_id"), "group_size")

    def texts(self, docs: DataFrame, text_col: str) -> DataFrame:
        return docs.withColumn("text", text_or_empty(text_col)).withColumn("digest", self.key(F.unhex(F.sha2("text", 256))))

    def mixed(self, docs: DataFrame, text_col: str = "text") -> DataFrame:
        """Byte verification: the digests that different texts share (as a rule none).

        Only texts that pass the filter of repeated digests are moved, and copies collapse before the shuffle."""
        repeated = self.compact().filter("group_size > 1").select("digest")
        hits = KeyFilter(repeated, "digest").prune(self.texts(docs.select(text_col), text_col).select("digest", "text"), "digest")
        return hits.groupBy("digest").agg(F.min("text").alias("low"), F.max("text").alias("high")).filter("low <> high").select("digest")


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest", digest_bytes: int = 32) -> DataFrame:
    """One row for each input row: doc_id, keep_id, group_size, kept, text_sha256."""
    index = DigestIndex(docs.sparkSession, keep, digest_bytes)
    index.flush(docs, id_col, text_col)
    level = index.compact()
    mixed = written(index.mixed(docs, text_col), "digest-mixed")
    rows = index.entries().drop("n")
    if mixed.isEmpty():
        found = rows.join(level, "digest")
    else:
        # Rare: a digest of several texts. Its rows are grouped by their bytes.
        told = index.texts(docs.select(F.col(id_col).cast("long").alias("id"), text_col), text_col).select("id", "digest", "text")
        told = written(told.join(mixed, "digest", "left_semi").withColumn("place", F.monotonically_increasing_id()), "digest-told")
        exact = told.groupBy("digest", "text").agg(index.first().alias("best"), F.count(F.lit(1)).alias("group_size"))
        exact = exact.select("digest", "text", F.col("best.id").alias("keep_id"), F.col("best.place").alias("keep_place"), "group_size")
        apart = told.join(exact, ["digest", "text"]).select("digest", "id", "place", F.unhex(F.sha2("text", 256)).alias("sha"), "keep_id", "keep_place", "group_size")
        found = rows.join(mixed, "digest", "left_anti").join(level, "digest").unionByName(apart)
    return found.select(
        F.col("id").alias("doc_id"),
        "keep_id",
        "group_size",
        (F.col("id").eqNullSafe(F.col("keep_id")) & (F.col("place") == F.col("keep_place"))).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
    )
