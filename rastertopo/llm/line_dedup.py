"""Line dedup: repeated runs of lines, found wherever they start.

A run of several lines of at least ``LEAST_WORDS`` words in all, or a line of ``HEAVY_WORDS`` words or more, that occurs
earlier anywhere, by (doc_id, text, place), is removed (``drop_passages``). Each repeated run is the union of its shortest
pieces that reach the threshold: for each line the shortest one that begins there and the shortest one that ends there.
Whether a piece occurs earlier needs no look at its neighbours, so a run goes whole, whatever stands around it, and nothing
goes that is not part of a repeated run. The first occurrence of each line stays.

``drop_repeated`` alone takes content-defined chunks for pieces instead: a rolling hash over the hashes of the last two
lines tells where a chunk ends, and a line of ``HEAVY_WORDS`` words or more is a chunk of its own. That leaves most lines of
repeated passages, so the queries don't use it.

Pieces are found by a digest and compared byte by byte before any is removed. Pieces of a digest are counted and compared
with partial aggregates; texts without a repeated piece pass without a shuffle, and the others are joined to the lines
to drop.

Cases: a null text stays null and an empty one empty; a text whose lines all go becomes empty, its row stays; rows
equal in doc_id and text are treated alike; a null doc_id comes first in order; an empty table gives an empty result;
other columns stay as they are, and columns that begin with "_" are reserved.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import KeyFilter, slices, written

HEAVY_WORDS, LEAST_WORDS, DIVISOR = 50, 10, 2
DIGEST_BYTES = 16
MASK, MULTIPLIER = (1 << 64) - 1, 0x9E3779B97F4A7C15


def chunk_spans(text: str, divisor: int = DIVISOR) -> list[tuple[int, int, int]]:
    """The chunks of a text as (first line, line after the last, words)."""
    spans, start, words, previous = [], 0, 0, 0
    for i, line in enumerate(text.split("\n")):
        n = len(line.split())
        if n >= HEAVY_WORDS:
            if start < i:
                spans.append((start, i, words))
            spans.append((i, i + 1, n))
            start, words, previous = i + 1, 0, 0
            continue
        words += n
        own = int.from_bytes(hashlib.blake2b(line.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big")
        rolled = (previous * MULTIPLIER + own) & MASK
        if (rolled >> 32) % divisor == 0:
            spans.append((start, i + 1, words))
            start, words = i + 1, 0
        previous = own
    last = text.count("\n") + 1
    if start < last:
        spans.append((start, last, words))
    return spans


def eligible(first: int, after: int, words: int) -> bool:
    return words >= LEAST_WORDS and (after - first > 1 or words >= HEAVY_WORDS)


def chunk_pieces(text: str) -> list[tuple[int, int]]:
    return [(a, b) for a, b, words in chunk_spans(text) if eligible(a, b, words)]


def run_pieces(text: str) -> list[tuple[int, int]]:
    """The shortest eligible runs of lines that begin or end at each line, and the heavy lines, as (first, after).

    A run of lines is a union of these if and only if it is eligible."""
    sums = [0]
    for line in text.split("\n"):
        sums.append(sums[-1] + len(line.split()))
    n = len(sums) - 1
    found = {(i, i + 1) for i in range(n) if sums[i + 1] - sums[i] >= HEAVY_WORDS}
    after = 0
    for first in range(n - 1):
        after = max(after, first + 2)
        while after <= n and sums[after] - sums[first] < LEAST_WORDS:
            after += 1
        if after > n:
            break
        found.add((first, after))
    first = 0
    for after in range(2, n + 1):
        while first + 1 < after - 1 and sums[after] - sums[first + 1] >= LEAST_WORDS:
            first += 1
        if sums[after] - sums[first] >= LEAST_WORDS:
            found.add((first, after))
    return sorted(found)


def chunks(docs: DataFrame, digest_bytes: int = DIGEST_BYTES, pieces=chunk_pieces) -> DataFrame:
    """The removable pieces of docs (doc_id, text): doc_id, twin, first, after, digest, piece."""

    def task(batches):
        import pyarrow as pa

        for batch in slices(batches):
            owner, first, after, digest, piece = [], [], [], [], []
            for row, text in enumerate(batch.column(2).to_pylist()):
                if not text:
                    continue
                lines = text.split("\n")
                for a, b in pieces(text):
                    part = "\n".join(lines[a:b])
                    owner.append(row)
                    first.append(a)
                    after.append(b)
                    piece.append(part)
                    digest.append(hashlib.blake2b(part.encode("utf-8", "surrogatepass"), digest_size=digest_bytes).digest())
            rows = pa.array(owner, pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(rows), batch.column(1).take(rows), pa.array(first, pa.int32()), pa.array(after, pa.int32()), pa.array(digest, pa.binary()), pa.array(piece, pa.string())],
                ["doc_id", "twin", "first", "after", "digest", "piece"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("twin"), "text")
    return rows.mapInArrow(task, "doc_id long, twin long, first int, after int, digest binary, piece string")


def repeated_lines(docs: DataFrame, digest_bytes: int = DIGEST_BYTES, pieces=chunk_pieces) -> DataFrame:
    """The lines to drop: doc_id, twin, drop array<struct<first, after>>; one row for each text that loses some."""
    found = written(chunks(docs, digest_bytes, pieces), "line-chunks")
    # Pieces of several lengths may begin at one line; they differ in their digests.
    place = F.struct("doc_id", "twin", "first")

    def first_of(rows: DataFrame, *by: str) -> DataFrame:
        return rows.groupBy(*by).agg(F.min(place).alias("kept"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")

    repeated = written(first_of(found.drop("piece"), "digest"), "line-repeated")
    hits = KeyFilter(repeated, "digest").prune(found.select("digest", "piece"), "digest")
    mixed = written(hits.groupBy("digest").agg(F.min("piece").alias("low"), F.max("piece").alias("high")).filter("low <> high").select("digest"), "line-mixed")
    light = found.drop("piece")
    if mixed.isEmpty():
        later = light.join(repeated.hint("merge"), "digest")
    else:
        # Rare: a digest of several pieces. Its chunks are grouped by their bytes.
        told = found.join(mixed, "digest", "left_semi")
        apart = told.join(first_of(told, "digest", "piece"), ["digest", "piece"]).drop("piece")
        later = light.join(repeated.join(mixed, "digest", "left_anti"), "digest").unionByName(apart)
    later = later.filter(~place.eqNullSafe(F.col("kept")))
    # At most the pieces of one text in a list.
    drops = later.groupBy("doc_id", "twin").agg(F.array_sort(F.collect_set(F.struct("first", "after"))).alias("drop"))
    return drops.withColumn("drop", disjoint(F.col("drop")))


def disjoint(spans: Column) -> Column:
    """Sorted spans, those that overlap made one."""

    def add(done: Column, s: Column) -> Column:
        last = F.get(done, F.size(done) - 1)
        longer = F.struct(last["first"].alias("first"), F.greatest(last["after"], s["after"]).alias("after"))
        joined = F.concat(F.slice(done, 1, F.size(done) - 1), F.array(longer))
        return F.when((F.size(done) > 0) & (s["first"] < last["after"]), joined).otherwise(F.concat(done, F.array(s)))

    return F.aggregate(spans, F.expr("cast(array() as array<struct<first: int, after: int>>)"), add)


def drop_passages(docs: DataFrame, digest_bytes: int = DIGEST_BYTES) -> DataFrame:
    """The input rows without repeated runs of lines; adds ``removed`` as ``drop_repeated`` does."""
    return drop_repeated(docs, digest_bytes, run_pieces)


def drop_repeated(docs: DataFrame, digest_bytes: int = DIGEST_BYTES, pieces=chunk_pieces) -> DataFrame:
    """The input rows without repeated pieces, chunks by default; adds ``removed`` array<struct<first, after>>: the lines that went."""
    lines = written(repeated_lines(docs, digest_bytes, pieces), "line-drops")
    key = F.xxhash64("doc_id", "twin")
    rows = docs.withColumn("_twin", F.xxhash64("text")).withColumn("_key", F.xxhash64(F.col("doc_id").cast("long"), F.col("_twin")))
    rows = KeyFilter(lines.withColumn("_key", key), "_key").flag(rows, "_key", "_may")
    drops = lines.select(F.col("doc_id").alias("_doc"), F.col("twin").alias("_other"), F.col("drop").alias("removed"))
    # The drops grow with the input, so they are never broadcast.
    touched = rows.filter("_may").join(drops.hint("merge"), F.col("doc_id").cast("long").eqNullSafe(F.col("_doc")) & (F.col("_twin") == F.col("_other")), "left")
    kept = F.filter(F.split("text", "\n", -1), lambda _, i: ~F.exists("removed", lambda s: (i >= s["first"]) & (i < s["after"])))
    text = F.when(F.col("removed").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n")).alias("text")
    others = [F.col(f"`{c}`") if c != "text" else text for c in docs.columns]
    same = rows.filter(~F.col("_may")).withColumn("removed", F.lit(None).cast(touched.schema["removed"].dataType))
    return same.select(*[F.col(f"`{c}`") for c in docs.columns], "removed").unionByName(touched.select(*others, "removed"))


def line_deduplicated(docs: DataFrame) -> DataFrame:
    """One row for each document: doc_id, text, n_lines, n_removed_lines, removed."""
    kept = drop_passages(docs.select("doc_id", "text"))
    gone = F.coalesce(F.aggregate("removed", F.lit(0), lambda n, s: n + s["after"] - s["first"]), F.lit(0)).cast("long")
    lines = F.when(F.length("text") > 0, F.size(F.split("text", "\n", -1)).cast("long")).otherwise(F.lit(0))
    return kept.select("doc_id", "text", lines.alias("n_lines"), gone.alias("n_removed_lines"), "removed")
