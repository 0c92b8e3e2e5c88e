"""WARC records as a chunked table: large payloads are rows of (record, chunk number), never one value.

A record's bytes are its chunks in order: the first starts with the header block, each further one goes on with the
payload. Every chunk carries the SHA-1 of the payload so far, so a reader that streams a record's chunks checks each
of them as it comes and holds one chunk at a time. Records of one chunk are read where they lie; only records of
several chunks are dealt out by record and sorted by chunk.
"""

from __future__ import annotations

import base64
import hashlib
import sys
import uuid

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import n_parts, shared_dir, small_batches, stored, table

cloudpickle.register_pickle_by_value(sys.modules[__name__])

CHUNK_BYTES = 256 * 1024
#: Equal payloads are kept once from this size on.
LEAST_REVISIT = 1000
#: Up to so many copied digests (about 60 bytes each) are sent to every task.
DIGESTS_SENT = 200_000
_FLUSH_BYTES = 8_000_000
_CHUNK_DDL = "record_id string, chunk_no bigint, several boolean, data binary, header_bytes int, payload_sha1 string"
_CHUNK_NAMES = ["record_id", "chunk_no", "several", "data", "header_bytes", "payload_sha1"]
_PAGE_DDL = "page_id bigint, target_uri string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, intact boolean"
_PAGE_NAMES = ["page_id", "target_uri", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact"]


def captures(pages: DataFrame) -> DataFrame:
    """pages (page_id, url, html) with payload_bytes, payload_digest, refers_to: which record each one revisits."""
    payload = F.coalesce(F.encode("html", "UTF-8"), F.lit(b""))
    x = pages.select("page_id", "url", "html", F.octet_length(payload).cast("bigint").alias("payload_bytes"), F.sha1(payload).alias("payload_digest"))
    small = x.select("page_id", "payload_bytes", "payload_digest").where(F.col("payload_bytes") >= LEAST_REVISIT)
    first = small.groupBy("payload_digest", "payload_bytes").agg(F.max("page_id").alias("kept"), F.count("*").alias("c")).where("c > 1").drop("c")
    first = stored(first, "copied")
    if first.count() <= DIGESTS_SENT:  # else the payloads are dealt out by digest
        first = F.broadcast(first)
    out = x.join(first, ["payload_digest", "payload_bytes"], "left")
    return out.withColumn("refers_to", F.when(~F.col("kept").eqNullSafe(F.col("page_id")), F.col("kept"))).drop("kept")


def _header(fields: list[tuple[str, str]]) -> bytes:
    lines = ["WARC/1.1", *(f"{k}: {v}" for k, v in fields)]
    return ("\r\n".join(lines) + "\r\n\r\n").encode()


def _one_line(text: str | None) -> str:
    return "" if text is None else text.replace("\r", "%0D").replace("\n", "%0A")


def _write(chunk_bytes: int):
    def run(batches):
        rows, held = [], 0

        def flush():
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            kinds = (pa.string(), pa.int64(), pa.bool_(), pa.binary(), pa.int32(), pa.string())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], _CHUNK_NAMES)

        for batch in batches:
            names = ("rid", "page_id", "url", "payload_bytes", "payload_digest", "refers_to")
            for i, (rid, page, url, size, digest, refers) in enumerate(zip(*(batch.column(n).to_pylist() for n in names), strict=True)):
                html = batch.column("html")[i]
                payload = memoryview(html.as_buffer()) if html.is_valid and refers is None else memoryview(b"")
                record = str(uuid.uuid5(uuid.NAMESPACE_URL, f"{rid} {page} {url} {digest}"))
                fields = [
                    ("WARC-Type", "response" if refers is None else "revisit"),
                    ("WARC-Record-ID", f"<urn:uuid:{record}>"),
                    ("WARC-Date", "1970-01-01T00:00:00Z"),
                    ("WARC-Target-URI", _one_line(url)),
                    ("Content-Type", "text/html; charset=utf-8"),
                    ("WARC-Payload-Digest", "sha1:" + base64.b32encode(bytes.fromhex(digest)).decode()),
                    ("X-Page-ID", "" if page is None else str(page)),
                    ("X-Payload-Length", str(size)),
                ]
                if refers is not None:
                    fields += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("X-Refers-To-Page-ID", str(refers))]
                head = _header([*fields, ("Content-Length", str(len(payload)))])
                sha, n = hashlib.sha1(), max(1, -(-len(payload) // chunk_bytes))
                for c in range(n):
                    part = payload[c * chunk_bytes : (c + 1) * chunk_bytes]
                    sha.update(part)
                    data = (head if c == 0 else b"") + bytes(part) + (b"\r\n\r\n" if c == n - 1 else b"")
                    rows.append((record, c, n > 1, data, len(head) if c == 0 else 0, sha.hexdigest()))
                    held += len(data)
                    if held > _FLUSH_BYTES:
                        yield flush()
                        rows.clear()
                        held = 0
        yield flush()

    return run


def _page(fields: dict, size: int, sha1: str, ok: bool) -> tuple:
    """What a record says; payload size and digest are recomputed for responses."""
    kind = fields["WARC-Type"]
    said = base64.b32decode(fields["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    number = lambda name: int(fields[name]) if fields.get(name) else None
    if kind == "response":
        ok &= said == sha1 and size == int(fields["Content-Length"])
    else:
        size, sha1 = int(fields["X-Payload-Length"]), said
    return number("X-Page-ID"), fields["WARC-Target-URI"], size, sha1, kind, number("X-Refers-To-Page-ID"), ok


def _read(batches):
    """Streams chunks, each record's in order; holds one chunk and a running digest."""
    fields, sha, size, ok, left, record = None, None, 0, True, 0, None
    for batch in batches:
        rows = []
        for i in range(batch.num_rows):
            data, cut = memoryview(batch.column("data")[i].as_buffer()), 0
            number, name = batch.column("chunk_no")[i].as_py(), batch.column("record_id")[i].as_py()
            if number == 0:
                if fields is not None:
                    rows.append(_page(fields, size, sha.hexdigest(), False))  # the record before had no end
                cut = batch.column("header_bytes")[i].as_py()
                lines = bytes(data[:cut]).decode().split("\r\n")[1:-2]
                fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines)
                sha, size, ok, left, record = hashlib.sha1(), 0, True, int(fields["Content-Length"]), name
            elif fields is None or name != record:
                raise ValueError(f"record {name} starts with chunk {number}")
            part = data[cut : cut + left]
            sha.update(part)
            size += len(part)
            left -= len(part)
            ok &= sha.hexdigest() == batch.column("payload_sha1")[i].as_py()
            if left == 0:
                rows.append(_page(fields, size, sha.hexdigest(), ok and bytes(data[cut + len(part) :]) == b"\r\n\r\n"))
                fields = None
        yield _pages(rows)
    if fields is not None:
        yield _pages([_page(fields, size, sha.hexdigest(), False)])


def _pages(rows: list) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * 7
    kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.bool_())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], _PAGE_NAMES)


def write_archive(pages: DataFrame, path: str, chunk_bytes: int = CHUNK_BYTES) -> None:
    """Writes one record per row of pages (page_id, url, html) to a chunk table at path.

    Of records with equal payloads of LEAST_REVISIT bytes at least, that with the largest page_id is a response and
    the others revisit it; rows that repeat this page_id are responses too. A null html is an empty payload; rows of a
    null page_id revisit a like payload that has one. Other columns are ignored.
    """
    small_batches(pages.sparkSession)
    packed = captures(pages.select(F.col("page_id").cast("bigint").alias("page_id"), "url", "html"))
    packed = packed.withColumn("rid", F.monotonically_increasing_id())
    chunks = packed.mapInArrow(_write(chunk_bytes), _CHUNK_DDL)
    chunks.write.option("compression", "zstd").partitionBy("several").parquet(path)


def read_archive(spark: SparkSession, path: str) -> DataFrame:
    """One row per record: page_id, target_uri, payload_bytes, payload_digest, record_type, refers_to, intact.

    intact tells whether every chunk met its running digest and the whole its header. Rows that were written twice
    are two records.
    """
    chunks = spark.read.schema("record_id string, chunk_no bigint, data binary, header_bytes int, payload_sha1 string, several boolean").parquet(path)
    alone = chunks.where(~F.col("several")).drop("several").mapInArrow(_read, _PAGE_DDL)
    many = chunks.where("several").drop("several").repartition(n_parts(spark), "record_id").sortWithinPartitions("record_id", "chunk_no")
    return alone.union(many.mapInArrow(_read, _PAGE_DDL))


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/treeline-warc-{uuid.uuid4().hex}"
    write_archive(table(spark, sf_dir, "pages"), path)
    return read_archive(spark, path).drop("target_uri", "intact")


OP3_SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages
), k AS (
  SELECT *, CASE WHEN payload_bytes >= 1000 THEN max(page_id) OVER (PARTITION BY payload_digest, payload_bytes) ELSE page_id END AS kept FROM p
)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
  CASE WHEN kept = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN kept <> page_id THEN kept END AS refers_to
FROM k
"""
