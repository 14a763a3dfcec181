"""WARC archives with resolved revisits: headers are shuffled by payload digest.

Payloads stay where they are as long as the digests that several records share fit into a broadcast of checked size;
beyond it the records are joined to them by digest. An archive is one gzip member: Spark's text writer, which commits
to any file system, closes a member only with its file.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import shared_dir, stored

#: Payloads below this many bytes are always written whole.
LEAST_BYTES = 100
#: Records below so many bytes of payload go to archives of so many records, the rest one by one; an archive has 256 MB at most, or one record.
ARCHIVES = ((1 << 16, 4096), (1 << 22, 64))
#: So many shared digests at most are broadcast (some 100 bytes each).
MOST_BROADCAST = 500_000
#: Bytes of an archive that are unpacked at once, and bytes of payload in a batch that is read back.
PIECE, BATCH = 1 << 20, 1 << 23
#: All records carry this date, so that a rewrite gives equal bytes.
DATE = "2024-01-01T00:00:00Z"

RECORD = T.StructType([
    T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("payload", T.StringType()),
    T.StructField("payload_bytes", T.LongType()), T.StructField("payload_digest", T.StringType()),
    T.StructField("record_type", T.StringType()), T.StructField("refers_to", T.LongType()),
])
ARROW = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])


def originals(headers: DataFrame, least: int = LEAST_BYTES) -> DataFrame:
    """Digest and smallest page_id of payloads that two or more records share; one row per such digest.

    The count is combined before the shuffle, so a digest that a third of all records have costs a row per task.
    """
    return (
        headers.where((F.col("payload_bytes") >= least) & F.col("page_id").isNotNull())
        .groupBy("payload_digest")
        .agg(F.min("page_id").alias("original"), F.count(F.lit(1)).alias("n"))
        .where("n > 1")
        .select("payload_digest", "original")
    )


def resolved(pages: DataFrame, least: int = LEAST_BYTES) -> DataFrame:
    """``pages`` (page_id, url, html) with payload, its size and digest, record type and the original it refers to.

    A null html is an empty payload. Of equal payloads of ``least`` bytes or more the smallest page_id
    is the response and others are revisits; rows that repeat that page_id, or have none, are written
    whole. Only digests met twice or more are stored and joined: broadcast up to ``MOST_BROADCAST``, beyond it by a
    join whose small side is read from a table, so that adaptive execution may split a hot digest.
    """
    payload = F.coalesce(F.col("html").cast("string"), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload"))
    rows = rows.withColumns({"payload_bytes": F.octet_length("payload").cast("long"), "payload_digest": F.sha2("payload", 256)})
    firsts = stored(originals(rows.select("page_id", "payload_bytes", "payload_digest"), least), "warc-originals")
    if firsts.count() <= MOST_BROADCAST:
        firsts = F.broadcast(firsts)
    again = (F.col("payload_bytes") >= least) & (F.col("page_id") != F.col("original"))
    return rows.join(firsts, "payload_digest", "left").select(
        "page_id", "url", "payload", "payload_bytes", "payload_digest",
        F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("original")).alias("refers_to"),
    )


def _one_line(name: str) -> Column:
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(name, "%", "%25"), "\r", "%0D"), "\n", "%0A")


def record_text() -> Column:
    """One record without the two line ends that close it: fresh headers, an empty line, then the block."""
    field = lambda name, value: F.when(value.isNotNull(), F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))).otherwise("")
    whole = F.col("record_type") == "response"
    return F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), F.col("record_type"), F.lit(f"\r\nWARC-Date: {DATE}\r\n"),
        field("WARC-Record-ID", F.concat(F.coalesce(F.concat(F.lit("<urn:page:"), F.col("page_id").cast("string")), F.concat(F.lit("<urn:nameless:"), F.monotonically_increasing_id().cast("string"))), F.lit(">"))),
        field("WARC-Target-URI", F.when(F.col("url").rlike("[\r\n]"), _one_line("url")).otherwise(F.col("url"))),
        F.when(F.col("url").rlike("[\r\n]"), "X-Target-URI-Encoded: yes\r\n").otherwise(""),
        F.lit("WARC-Payload-Digest: sha256:"), F.col("payload_digest"), F.lit("\r\n"),
        F.when(whole, "").otherwise("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest\r\n"),
        field("WARC-Refers-To", F.concat(F.lit("<urn:page:"), F.col("refers_to").cast("string"), F.lit(">"))),
        F.when(whole, "").otherwise(F.concat(F.lit("X-Payload-Length: "), F.col("payload_bytes").cast("string"), F.lit("\r\n"))),
        F.lit("Content-Length: "), F.when(whole, F.col("payload_bytes")).otherwise(0).cast("string"),
        F.lit("\r\n\r\n"), F.when(whole, F.col("payload")).otherwise(""),
    )


def write_archives(records: DataFrame, path: str, archives: tuple[tuple[int, int], ...] = ARCHIVES, sizes: DataFrame | None = None) -> None:
    """Gzipped archives, written by Spark's own committer to any file system: a lost task leaves no half archive.

    They are cut by bytes: records of each class of sizes that occurs are written by themselves, many small ones to an archive.
    ``sizes`` has the payload_bytes of the records, if these are dear to compute.
    """
    size = sum((F.when(F.col("payload_bytes") >= least, 1).otherwise(0) for least, _ in archives), F.lit(0))
    found = {r["size"] for r in (sizes or records).select(size.alias("size")).groupBy("size").count().collect()}  # a row for each class at most
    for k, most in enumerate([*(n for _, n in archives), 1]):
        if k in found or not k:
            rows = records.where(size == k) if len(found) > 1 else records
            rows.select(record_text().alias("value")).write.option("lineSep", "\r\n\r\n").option("compression", "gzip").option("maxRecordsPerFile", most).text(f"{path}/size-{k}")


def unpacked(data: bytes) -> Iterator[bytes]:
    """The content of an archive of one or more gzip members, piece by piece."""
    part = zlib.decompressobj(31)
    for at in range(0, len(data), PIECE):
        rest = data[at : at + PIECE]
        while rest:
            yield part.decompress(rest, 4 * PIECE)
            rest = part.unconsumed_tail
            if part.eof:
                rest, part = part.unused_data, zlib.decompressobj(31)


def split_records(pieces: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (lower-case names) and block of each record; blocks are cut by Content-Length alone.

    No more than a record and a piece is held.
    """
    held, at = bytearray(), 0

    def has(size: int) -> bool:
        """Whether ``size`` bytes from the record's begin on are there, or can be had."""
        nonlocal held, at
        while len(held) - at < size:
            piece = next(pieces, None)
            if piece is None:
                return False
            del held[:at]
            at = 0
            held += piece
        return True

    while has(1):
        size = 4096
        while (stop := held.find(b"\r\n\r\n", at)) < 0:
            if not has(size := max(size, len(held) - at + 1)):
                raise ValueError("an archive ends within a record's head")
        first, *lines = held[at:stop].decode().split("\r\n")
        if not first.startswith("WARC/"):
            raise ValueError("no WARC record where one should begin")
        fields = {k.lower(): v for k, v in (line.split(": ", 1) for line in lines)}
        head, length = stop + 4 - at, int(fields["content-length"])
        if not has(head + length):
            raise ValueError("an archive ends within a record")
        yield fields, bytes(held[at + head : at + head + length])
        has(head + length + 4)
        at += head + length + 4


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Records of all archives under ``path``; digest and size of a response come from its block."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = lambda x: int(x[len("<urn:page:") : -1]) if x and x.startswith("<urn:page:") else None
        for batch in batches:
            for content in batch.column(0):
                out, held = [], 0
                for fields, block in split_records(unpacked(content.as_py())):
                    url = fields.get("warc-target-uri")
                    if "x-target-uri-encoded" in fields:
                        url = url.replace("%0A", "\n").replace("%0D", "\r").replace("%25", "%")
                    whole = fields["warc-type"] == "response"
                    out.append({
                        "page_id": number(fields.get("warc-record-id")), "url": url, "payload": block.decode() if whole else None,
                        "payload_bytes": len(block) if whole else int(fields["x-payload-length"]), "payload_digest": hashlib.sha256(block).hexdigest() if whole else fields["warc-payload-digest"].removeprefix("sha256:"),
                        "record_type": fields["warc-type"], "refers_to": number(fields.get("warc-refers-to")),
                    })
                    held += len(block)
                    if len(out) == 500 or held > BATCH:
                        yield pa.RecordBatch.from_pylist(out, schema=ARROW)
                        out, held = [], 0
                yield pa.RecordBatch.from_pylist(out, schema=ARROW)

    return spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").option("recursiveFileLookup", "true").load(path).select("content").mapInArrow(work, RECORD)


def archived(pages: DataFrame, least: int = LEAST_BYTES) -> DataFrame:
    """Writes deduplicated archives of ``pages`` to the shared folder and returns their records as read back."""
    spark = pages.sparkSession
    path = f"{shared_dir(spark)}/warc/{uuid.uuid4().hex}"
    write_archives(resolved(pages, least), path, sizes=pages.select(F.octet_length(F.coalesce(F.col("html").cast("string"), F.lit(""))).alias("payload_bytes")))
    return read_archives(spark, path)
