"""WARC records as a chunked table.

A record is rows of (record_id, chunk_no): chunk 0 is the WARC header block and the first piece of the payload, the
others are further pieces of ``chunk_bytes``, and the last ends the record. Each row carries the SHA-1 of the payload up to and including it, so a
reader checks a stream piece by piece. Payloads are cut where they are read, in the JVM; Python gets pieces and carries a digest, so no
task builds a whole record. The rows of a record in the order of
chunk_no are the bytes of a WARC 1.1 file. The table is Parquet, committed by Spark, so lost tasks leave nothing.

Equal payloads of at least ``least_bytes`` bytes are stored once, in the response record of the largest page_id; the
others become revisit records that refer to it. Payloads are equal when length, SHA-1 and SHA-256 are. Only digests are
grouped; of equal payloads one is moved, and one that no other equals stays where it was read.

Cases: a null payload is empty; empty payloads are one row; rows that repeat the page_id and the
payload of a response are responses too; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import KeyFilter, scratch_path, slices, written

CHUNK_BYTES = 1 << 14
CHUNKS = "record_id string, serial long, page_id long, archive int, chunk_no int, last boolean, block binary, running_sha1 string"
CRLF = b"\r\n"


def base32(sha1: bytes) -> str:
    return base64.b32encode(sha1).decode("ascii")


def roles(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """pages (page_id, url, payload binary) with sha1, n_bytes and response_id: the page whose record holds the payload.

    The payload of a row that another row's record holds is null."""
    rows = pages.withColumn("n_bytes", F.octet_length("payload").cast("long")).withColumn("sha1", F.unhex(F.sha1("payload"))).withColumn("sha256", F.unhex(F.sha2("payload", 256)))
    same = ["n_bytes", "sha1", "sha256"]
    held = rows.filter(F.col("n_bytes") >= least_bytes).groupBy(*same).agg(F.max("page_id").alias("response_id"), F.count(F.lit(1)).alias("_n")).filter("_n > 1").drop("_n")
    held = written(held, "warc-held").withColumn("_lead", F.xxhash64("sha256", "response_id"))
    rows = KeyFilter(held, "sha256").flag(rows.withColumn("_lead", F.xxhash64("sha256", "page_id")), "sha256", "_may")
    rows = KeyFilter(held, "_lead").flag(rows, "_lead", "_leads").drop("_lead")
    alone = rows.filter(~F.col("_may")).withColumn("response_id", F.col("page_id"))
    # Rows that can't be the response go without their payload.
    moved = rows.filter("_may").withColumn("payload", F.when(F.col("_leads") | (F.col("n_bytes") < least_bytes), F.col("payload")))
    moved = moved.join(held.drop("_lead").hint("merge"), same, "left").withColumn("response_id", F.coalesce("response_id", "page_id"))
    found = alone.unionByName(moved).drop("sha256", "_may", "_leads")
    return found.withColumn("payload", F.when(F.col("response_id").eqNullSafe(F.col("page_id")), F.col("payload")))


def write_archive(pages: DataFrame, path: str, least_bytes: int = 0, chunk_bytes: int = CHUNK_BYTES) -> None:
    """Writes a record for each row of pages (page_id, url, html) to the chunk table at ``path``."""

    def task(batches):
        import pyarrow as pa

        names = ["record_id", "serial", "page_id", "archive", "chunk_no", "last", "block", "running_sha1"]
        types = [pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.binary(), pa.string()]
        running = hashlib.sha1()
        for batch in slices(batches):
            out = []
            for page, url, length, sha1, response, archive, record, target, serial, number, last, piece in zip(*(c.to_pylist() for c in batch.columns)):
                start = b""
                if number == 0:
                    running = hashlib.sha1()
                    start = header_block(record, url or "", length, base32(sha1), target if response != page else None)
                running.update(piece)
                out.append((record, serial, page, archive, number, last, start + piece + CRLF * 2 * last, base32(running.digest())))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("payload"))
    found = roles(rows, least_bytes)

    def name(page, sha1):
        digest = F.md5(F.concat_ws(":", F.coalesce(page.cast("string"), F.lit("null")), F.hex(sha1)))
        return F.concat(F.lit("urn:uuid:"), *[x for k, (a, b) in enumerate(((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))) for x in ((F.lit("-"),) if k else ()) + (F.substring(digest, a, b),)])

    found = found.withColumn("record_id", name(F.col("page_id"), F.col("sha1"))).withColumn("target", name(F.col("response_id"), F.col("sha1")))
    found = found.withColumn("archive", F.pmod(F.xxhash64("record_id"), F.lit(64)).cast("int")).withColumn("serial", F.monotonically_increasing_id())
    last = f"cast(greatest(octet_length(payload) - 1, 0) div {chunk_bytes} as int)"
    pieces = f"transform(sequence(0, coalesce({last}, 0)), i -> coalesce(substring(payload, i * {chunk_bytes} + 1, {chunk_bytes}), cast('' as binary)))"
    columns = ["page_id", "url", "n_bytes", "sha1", "response_id", "archive", "record_id", "target", "serial"]
    # The pieces of a record follow each other in the task that cuts them.
    cut = found.select(*columns, F.expr(f"coalesce({last}, 0)").alias("_last"), F.posexplode(F.expr(pieces)).alias("chunk_no", "piece"))
    cut.select(*columns, "chunk_no", (F.col("chunk_no") == F.col("_last")).alias("last"), "piece").mapInArrow(task, CHUNKS).write.parquet(path)


def header_block(record: str, url: str, length: int, digest: str, target: str | None) -> bytes:
    """The WARC header; ``target`` is the record that a revisit refers to (its own block is then empty)."""
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'response' if target is None else 'revisit'}",
        f"WARC-Record-ID: <{record}>",
        f"WARC-Target-URI: {' '.join(url.split())}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"X-Payload-Length: {length}",
    ]
    if target is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <{target}>"]
    lines += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {length if target is None else 0}", "", ""]
    return "\r\n".join(lines).encode()


def parse_header(block: bytes) -> dict[str, str]:
    version, _, rest = block.decode().partition("\r\n")
    if not version.startswith("WARC/"):
        raise ValueError("not a WARC record")
    return dict(line.split(": ", 1) for line in rest.split("\r\n") if ": " in line)


class _Reader:
    """Checks records that come as rows of ascending (record, chunk); keeps a digest, never a payload."""

    def __init__(self):
        self.header, self.running, self.length, self.expected = None, None, 0, 0

    def feed(self, page: int, number: int, last: bool, block: bytes, stated: str):
        body = block
        if number == 0:
            head, _, body = block.partition(CRLF * 2)
            self.header, self.running, self.length, self.expected = parse_header(head), hashlib.sha1(), 0, 0
        if self.header is None or number != self.expected:
            raise ValueError(f"page {page}: chunk {number} where {self.expected} was due")
        body = body[: -2 * len(CRLF)] if last else body
        self.running.update(body)
        self.length, self.expected = self.length + len(body), number + 1
        if base32(self.running.digest()) != stated:
            raise ValueError(f"page {page}: chunk {number} doesn't match its running digest")
        if not last:
            return None
        h, self.header = self.header, None
        stored, kind = h["WARC-Payload-Digest"].removeprefix("sha1:"), h["WARC-Type"]
        if self.length != int(h["Content-Length"]) or kind == "response" and base32(self.running.digest()) != stored:
            raise ValueError(f"page {page}: the payload doesn't match its header")
        return page, h["WARC-Record-ID"].strip("<>"), int(h["X-Payload-Length"]), stored, kind, h.get("WARC-Refers-To", "").strip("<>") or None


RECORDS = "page_id long, record_id string, payload_bytes long, payload_digest string, record_type string, refers_to_record string"


def _checked(batches):
    import pyarrow as pa

    types = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string())
    names = [x.split()[0] for x in RECORDS.split(", ")]
    reader = _Reader()
    for batch in slices(batches):
        columns = [batch.column(i) for i in range(batch.num_columns)]
        out = [x for i in range(batch.num_rows) if (x := reader.feed(*(c[i].as_py() for c in columns)))]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)
    if reader.header is not None:
        raise ValueError("the archive ends within a record")


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """Reads a chunk table back, checking every digest. Records of one chunk are checked where they lie; only those of
    several chunks are moved, to be read in order."""
    chunks = spark.read.schema(CHUNKS).parquet(path)
    fields = ["page_id", "chunk_no", "last", "block", "running_sha1"]
    whole = chunks.filter("chunk_no = 0 AND last").select(fields).mapInArrow(_checked, RECORDS)
    parts = chunks.filter("NOT (chunk_no = 0 AND last)").repartition("record_id", "serial").sortWithinPartitions("record_id", "serial", "chunk_no")
    return whole.unionByName(parts.select(fields).mapInArrow(_checked, RECORDS))


def round_trip(pages: DataFrame, least_bytes: int = 0, chunk_bytes: int = CHUNK_BYTES, path: str | None = None) -> DataFrame:
    """Writes the pages' archive, reads it back and tells each page's record: page_id, payload_bytes, payload_digest,
    record_type, refers_to (the page of the response that a revisit refers to)."""
    spark = pages.sparkSession
    path = path or scratch_path(spark, "warc")
    write_archive(pages, path, least_bytes, chunk_bytes)
    records = read_archive(spark, path).select("page_id", "record_id", "payload_bytes", "payload_digest", "record_type", "refers_to_record")
    records = written(records, "warc-records")
    responses = records.filter("record_type = 'response'").select(F.col("record_id").alias("refers_to_record"), F.col("page_id").alias("refers_to")).distinct()
    revisits = records.filter("record_type = 'revisit'").join(responses, "refers_to_record")
    answered = records.filter("record_type = 'response'").withColumn("refers_to", F.lit(None).cast("long"))
    columns = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    return answered.select(columns).unionByName(revisits.select(columns))


def export_files(spark: SparkSession, path: str, folder: str) -> DataFrame:
    """Streams the chunk table into WARC files of ``folder``, one for each archive number: archive, file, n_bytes.

    ``folder`` is a URI that pyarrow can open on the executors. A file gets its name when it is whole."""

    def task(key, batches):
        import uuid

        import pyarrow as pa
        import pyarrow.fs as fs

        store, base = fs.FileSystem.from_uri(folder)
        store.create_dir(base)
        target, n = f"{base}/part-{key[0].as_py():05d}.warc", 0
        draft = f"{target}.{uuid.uuid4().hex}"
        with store.open_output_stream(draft) as out:
            for batch in batches:
                for block in batch.column("block"):
                    out.write(block.as_buffer())
                    n += len(block.as_buffer())
        store.move(draft, target)
        yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([target]), pa.array([n], pa.int64())], ["archive", "file", "n_bytes"])

    chunks = spark.read.schema(CHUNKS).parquet(path)

    def partition(batches):
        import itertools

        import pyarrow as pa

        def rows():
            for batch in batches:
                numbers = batch.column(0).to_pylist()
                start = 0
                for number, run in itertools.groupby(numbers):
                    size = len(list(run))
                    yield number, batch.slice(start, size)
                    start += size

        for number, group in itertools.groupby(rows(), key=lambda x: x[0]):
            yield from task((pa.scalar(number),), (x[1] for x in group))

    ordered = chunks.repartition("archive").sortWithinPartitions("archive", "record_id", "serial", "chunk_no").select("archive", "block")
    return ordered.mapInArrow(partition, "archive int, file string, n_bytes long")


WARC_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS h FROM pages),
g AS (SELECT *, max(page_id) OVER (PARTITION BY body) AS held FROM p)
SELECT page_id, octet_length(encode(body))::BIGINT AS payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    (((('0x' || substr(h, ((i // 4) * 5 + 1)::INT, 5))::BIGINT >> (15 - 5 * (i % 4))::INT) & 31) + 1)::INT, 1)), '') AS payload_digest,
  CASE WHEN page_id = held THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = held THEN NULL ELSE held END AS refers_to
FROM g
"""
