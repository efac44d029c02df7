"""WARC archives with revisits resolved.

Headers (payload digest, size, id) are grouped by digest; of records with one payload that of the largest id stays a response and
the others become revisits that refer to it. Records are assembled by column expressions and written by Spark's own committed
writer, so a lost executor costs a task, never a torn archive; files have at most twice `file_bytes`, or one record. Reading walks the files by
Content-Length, so payloads may hold anything, and recomputes every payload's digest.

Defined cases: a null payload is the empty one; payloads shorter than `min_bytes` are never revisits; repeated rows of the
largest id are all responses; null urls get the record's own urn; line breaks in urls are removed; an empty table gives an empty
archive; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from datetime import datetime, timezone

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stages, bounded_batches, map_arrow, table

FILE_BYTES = 8 << 20
#: The profile of revisit records with an identical payload (fixed value of the format).
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
PARSED = "record_id string, record_type string, target_uri string, payload_bytes long, payload_digest string, refers_to string, payload binary"


def base32_sha1(data: Column) -> Column:
    """Upper-case base 32 of the SHA-1 of a string or binary column: 60, 60 and 40 bits as base-32 numbers, digits renamed."""
    digest = F.sha1(data)
    part = lambda at, n, to: F.lpad(F.conv(F.substring(digest, at, n), 16, 32), to, "0")
    return F.translate(F.upper(F.concat(part(1, 15, 12), part(16, 15, 12), part(31, 10, 8))), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def resolve_revisits(pages: DataFrame, *, key: str = "page_id", url: str = "url", payload: str = "html", min_bytes: int = 0, stages: Stages | None = None) -> DataFrame:
    """id, uri, payload, payload_bytes, payload_digest, refers_to, refers_uri (null for responses) of each row."""
    stages = stages or Stages(pages.sparkSession, "warc")
    clean = F.translate(F.coalesce(F.col(url), F.concat(F.lit("urn:x-page:"), F.coalesce(F.col(key).cast("string"), F.lit("null")))), "\r\n", "")
    body = F.coalesce(F.col(payload).cast("string"), F.lit(""))
    records = pages.select(F.col(key).alias("id"), clean.alias("uri"), body.alias("payload")).select(
        "*", F.octet_length("payload").cast("long").alias("payload_bytes"), base32_sha1(F.col("payload")).alias("payload_digest")
    )
    # written first: of a few repeated digests Spark then knows the size, and need not shuffle payloads to join them
    groups = stages.keep(
        records.where(F.col("payload_bytes") >= min_bytes).groupBy("payload_digest")
        .agg(F.max(F.struct("id", "uri")).alias("kept"), F.count(F.lit(1)).alias("n")).where("n > 1")
    )
    total = F.broadcast(pages.agg((F.count(F.lit(1)) / 1000).alias("least")))
    ranked = groups.crossJoin(total)  # over a thousandth of all rows: at most a thousand digests
    hot, cold = (ranked.where(c).select("payload_digest", F.col("kept").alias(n)) for c, n in (("n > least", "hot"), ("n <= least", "cold")))
    joined = records.join(F.broadcast(hot), "payload_digest", "left").join(cold, "payload_digest", "left")
    kept = F.coalesce("hot", "cold")
    older = F.col("id") < kept["id"]
    return joined.select("id", "uri", "payload", "payload_bytes", "payload_digest", F.when(older, kept["id"]).alias("refers_to"), F.when(older, kept["uri"]).alias("refers_uri"))


def write_warc(resolved: DataFrame, path: str, *, date: str | None = None, file_bytes: int = FILE_BYTES) -> None:
    """Writes one record per row of `resolve_revisits`."""
    date = date or datetime.now(timezone.utc).strftime("%Y-%m-%dT%H:%M:%SZ")
    ident = lambda c: F.concat(F.lit("<urn:x-page:"), F.coalesce(F.col(c).cast("string"), F.lit("null")), F.lit(">\r\n"))
    line = lambda name, c: F.concat(F.lit(f"{name}: "), c, F.lit("\r\n"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("payload_bytes").cast("string"), F.lit("\r\n\r\n"))
    again = F.col("refers_to").isNotNull()
    shared = lambda kind: [F.lit(f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Date: {date}\r\nWARC-Record-ID: "), ident("id"), line("WARC-Target-URI", F.col("uri")), line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))), F.lit("Content-Type: application/http;msgtype=response\r\n")]
    response = F.concat(*shared("response"), line("Content-Length", (F.octet_length("http") + F.col("payload_bytes")).cast("string")), F.lit("\r\n"), F.col("http"), F.col("payload"), F.lit("\r\n"))
    revisit = F.concat(*shared("revisit"), F.lit(f"WARC-Profile: {PROFILE}\r\nWARC-Refers-To: "), ident("refers_to"), line("WARC-Refers-To-Target-URI", F.col("refers_uri")), line("Content-Length", F.octet_length("http").cast("string")), F.lit("\r\n"), F.col("http"), F.lit("\r\n"))
    # A task writes a file for each power of two of sizes and each run of so many rows that those of the size fill `file_bytes`: a file
    # has at most twice that, or one record, however sizes are mixed
    row = F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)
    power = F.greatest(F.lit(12), F.floor(F.log2(F.col("payload_bytes").cast("double") + 1024)).cast("int"))
    run = F.floor(row / F.greatest(F.lit(1.0), F.lit(float(file_bytes)) / F.pow(F.lit(2.0), power))).cast("long")
    records = resolved.select("*", power.alias("power"), run.alias("run")).withColumn("http", http)
    records = records.select(F.when(again, revisit).otherwise(response).alias("value"), "power", "run")
    records.write.partitionBy("power", "run").option("lineSep", "\r\n").text(path)


def parse_warc(data: bytes) -> Iterator[dict]:
    """The records of an uncompressed archive, found by Content-Length."""
    at, end = 0, len(data)
    while at < end:
        stop = data.index(b"\r\n\r\n", at)
        head = data[at:stop].split(b"\r\n")
        if not head[0].startswith(b"WARC/"):
            raise ValueError(f"no record at byte {at}")
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in head[1:])}
        length = int(fields[b"content-length"])
        yield {"fields": fields, "block": data[stop + 4 : stop + 4 + length]}
        at = stop + 4 + length
        while data.startswith(b"\r\n", at):
            at += 2


def read_warc(spark: SparkSession, path: str, *, payloads: bool = True) -> DataFrame:
    """The records under `path`; with `payloads` false, digests are still checked but payloads are not returned."""
    bounded_batches(spark, 2)

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plain = lambda b: b.decode("utf-8", "replace") if b is not None else None
        for batch in batches:
            for content in batch.column(0):
                rows: list[tuple] = []
                for r in parse_warc(content.as_py()):
                    f, block = r["fields"], r["block"]
                    cut = block.index(b"\r\n\r\n") + 4
                    size = int(next(x for x in block[:cut].lower().split(b"\r\n") if x.startswith(b"content-length:")).partition(b":")[2])
                    digest = plain(f[b"warc-payload-digest"]).removeprefix("sha1:")
                    payload = block[cut:] if f[b"warc-type"] == b"response" else None
                    if payload is not None and (len(payload) != size or base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest):
                        raise ValueError(f"payload of {f[b'warc-record-id']!r} does not match its digest")
                    rows.append((plain(f[b"warc-record-id"]), plain(f[b"warc-type"]), plain(f.get(b"warc-target-uri")), size, digest, plain(f.get(b"warc-refers-to")), payload if payloads else None))
                columns = list(zip(*rows, strict=True)) if rows else [[]] * 7
                kinds = [pa.string(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in PARSED.split(", ")])

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return map_arrow(files, body, PARSED)


def page_number(urn: str) -> Column:
    return F.regexp_extract(urn, r"x-page:(-?\d+)", 1).try_cast("long")


def op4_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    stages = Stages(spark, "warc")
    path = f"{stages.root}/archive"
    write_warc(resolve_revisits(table(spark, sf_dir, "pages").select("page_id", "url", "html"), stages=stages), path)
    return read_warc(spark, path, payloads=False).select(page_number("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", page_number("refers_to").alias("refers_to"))


OP4_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (
  SELECT page_id, strlen(html) AS payload_bytes, array_to_string(list_transform(range(0, 32), lambda i:
    substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + (((('0x' || substr(sha1(html), 5 * (i // 4)::INT + 1, 5))::BIGINT >> (15 - 5 * (i % 4))::INT) & 31))::INT, 1)), '') AS payload_digest
  FROM p),
k AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS kept FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id < kept THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id < kept THEN kept END AS refers_to FROM k
"""
