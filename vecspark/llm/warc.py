"""WARC archives with revisit resolution.

Headers (page, digest, length) alone are shuffled by payload digest; of equal payloads the record with the
largest page id is the response and the others become revisit records that refer to it and carry no payload.
Archives are plain WARC/1.1 records in gzip files in the cluster's shared folder, each with headers of its own;
they are read back record by record.

Defined results: a null html is the empty payload; rows that repeat a page id with the same payload are of one
kind; a null page id is smaller than all others; control characters in a url are percent-encoded; payloads
below `min_bytes` are all responses.  An empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import new_path, settle, table

#: The digits of Java's radix 32 and of base32, in order.
RADIX_32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV"
BASE_32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"

FILE_BYTES = 32 << 20
END = "\r\n"


def sha1_base32(payload: Column) -> Column:
    """Every 5 of the 40 hexadecimal digits are 4 base32 digits."""
    digest = F.sha1(payload)
    parts = [F.lpad(F.conv(F.substring(digest, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.upper(F.concat(*parts)), RADIX_32, BASE_32)


def with_digest(pages: DataFrame) -> DataFrame:
    payload = F.coalesce(F.col("html").cast("string"), F.lit(""))
    url = F.regexp_replace(F.col("url").cast("string"), r"[\x00-\x20\x7F]", "%20")
    out = pages.select(F.col("page_id").cast("long").alias("page_id"), url.alias("url"), payload.alias("payload"))
    return out.withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("payload_digest", sha1_base32(F.col("payload").cast("binary")))


def resolve_revisits(headers: DataFrame, min_bytes: int = 0) -> DataFrame:
    """page_id, payload_digest, payload_bytes -> the same, distinct, with record_type and refers_to."""
    keys = ["payload_digest", "payload_bytes"]
    originals = settle(headers.where(F.col("payload_bytes") >= min_bytes).groupBy(*keys).agg(F.max("page_id").alias("original"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n"), "warc-originals")
    found = headers.select("page_id", *keys).join(originals, keys, "left")
    again = F.col("original").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("original"))
    return found.select("page_id", *keys, F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("original")).alias("refers_to")).distinct()


def record_text(kind: Column) -> Column:
    """A whole record but for its last two line ends, which the writer puts between records."""
    response = kind == "response"
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{END}Content-Type: text/html; charset=utf-8{END}Content-Length: "), F.col("payload_bytes").cast("string"), F.lit(END + END))
    block = F.when(response, F.concat(http, F.col("payload"))).otherwise(F.lit(""))
    name = F.coalesce(F.col("page_id").cast("string"), F.lit("null"))
    line = lambda key, value: F.concat(F.lit(f"{key}: "), value, F.lit(END))
    return F.concat(
        F.lit(f"WARC/1.1{END}"),
        line("WARC-Type", kind),
        line("WARC-Record-ID", F.concat(F.lit("<urn:page:"), name, F.lit(">"))),
        F.when(F.col("url").isNotNull(), line("WARC-Target-URI", F.col("url"))).otherwise(F.lit("")),
        line("WARC-Date", F.lit("2024-01-01T00:00:00Z")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))),
        line("X-Payload-Length", F.col("payload_bytes").cast("string")),
        F.when(response, F.lit("")).otherwise(F.concat(F.lit(f"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest{END}WARC-Refers-To: <urn:page:"), F.col("refers_to").cast("string"), F.lit(f">{END}"))),
        F.when(response, F.lit(f"Content-Type: application/http; msgtype=response{END}")).otherwise(F.lit("")),
        line("Content-Length", F.octet_length(block).cast("string")),
        F.lit(END),
        block,
    )


def write_archives(pages: DataFrame, path: str, min_bytes: int = 0) -> None:
    """One deduplicated archive file or more for each partition, of about FILE_BYTES of records."""
    dated = with_digest(pages)
    headers = settle(dated.select("page_id", "payload_digest", "payload_bytes"), "warc-headers")
    size = headers.agg(F.avg(F.col("payload_bytes")).alias("mean")).first()["mean"] or 1.0
    kinds = resolve_revisits(headers, min_bytes)
    key = lambda df: df.withColumn("__key", F.coalesce(F.col("page_id"), F.lit(-(1 << 62))))
    records = key(dated).join(key(kinds).drop("page_id", "payload_bytes"), ["__key", "payload_digest"]).select(record_text(F.col("record_type")).alias("value"))
    records.write.option("lineSep", END + END).option("compression", "gzip").option("maxRecordsPerFile", max(1, int(FILE_BYTES / (size + 500)))).text(path)


def parse_records(content: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, block) of each record of a gzip archive."""
    out, rest = [], content
    while rest:
        z = zlib.decompressobj(31)
        out.append(z.decompress(rest) + z.flush())
        rest = z.unused_data
    data = b"".join(out)
    at = 0
    while at < len(data):
        to = data.index(b"\r\n\r\n", at)
        head = dict(x.split(": ", 1) for x in data[at:to].decode("utf-8").split(END)[1:])
        n = int(head["Content-Length"])
        yield head, data[to + 4 : to + 4 + n]
        at = to + 4 + n + 4


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """page_id, url, payload_bytes, payload_digest, record_type, refers_to, html (null for a revisit)."""

    def number(text: str | None) -> int | None:
        text = (text or "").removeprefix("<urn:page:").removesuffix(">")
        return int(text) if text and text != "null" else None

    def parsed(batches):
        names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "html"]
        types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
        for batch in batches:
            for content in batch.column(0):
                rows: list[list] = [[] for _ in names]
                held = 0
                for head, block in parse_records(content.as_py()):
                    whole = head["WARC-Type"] == "response"
                    body = block[block.index(b"\r\n\r\n") + 4 :] if whole else None
                    digest = base64.b32encode(hashlib.sha1(body).digest()).decode() if whole else head["WARC-Payload-Digest"].removeprefix("sha1:")
                    values = (number(head["WARC-Record-ID"]), head.get("WARC-Target-URI"), len(body) if whole else int(head["X-Payload-Length"]), digest, head["WARC-Type"], number(head.get("WARC-Refers-To")), body.decode("utf-8", "replace") if whole else None)
                    for column, value in zip(rows, values, strict=True):
                        column.append(value)
                    held += len(block)
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types, strict=True)], names=names)
                        rows, held = [[] for _ in names], 0
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types, strict=True)], names=names)

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.gz").load(path)
    return files.select("content").mapInArrow(parsed, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, html string")


def op8_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "warc")
    write_archives(table(spark, sf_dir, "pages"), path)
    return read_archives(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP8_SQL = """
WITH hashed AS (
  SELECT page_id, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS payload_bytes, sha1(coalesce(html, '')) AS hex FROM pages
), digested AS (
  SELECT page_id, payload_bytes, list_aggregate(list_transform(range(32), lambda i:
    substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST((CAST(('0x' || substr(hex, 5 * (i // 4) + 1, 5)) AS BIGINT) >> (5 * (3 - i % 4))) & 31 AS INTEGER), 1)), 'string_agg', '') AS payload_digest
  FROM hashed
)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN page_id = max(page_id) OVER w THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> max(page_id) OVER w THEN max(page_id) OVER w END AS refers_to
FROM digested WINDOW w AS (PARTITION BY payload_digest, payload_bytes)
"""
