"""WARC archives with revisit resolution.

Headers (page id and payload digest) are shuffled by digest; of equal payloads the one with the largest page_id is the
response, and every other record revisits it. Archives are then written with fresh headers: full HTTP responses, and
revisit records that hold HTTP headers only and name the response they refer to. `read_archives` parses them back.

Archives are the part files of Spark's text writer (gzip), of `ARCHIVE_RECORDS` records at most, in the shared folder. They are
read as a stream: a task holds a batch of pieces and the record it is in, however long the archive is.
The counts of equal digests combine before their shuffle; large groups of equal pages meet only in a join that adaptive
execution can split.

Defined results: a null html is an empty payload; payloads below `least_bytes` are all responses; rows that repeat the
largest page_id of their payload are all responses; a null page_id is the smallest of all and is written as `null`; null
urls give an empty target; an empty table gives no records; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch.llm.common import ensure_checkpoint_dir

#: The base-32 alphabet, and the digits that conv() gives for base 32.
BASE32, DIGITS32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "0123456789ABCDEFGHIJKLMNOPQRSTUV"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"
ARCHIVE_RECORDS = 5_000
LEAST_BYTES = 0
END = "\r\n\r\n"
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, archive string"


def sha1_base32(payload):
    """Native: 20 bytes as 32 base-32 digits, four for each five hexadecimal ones."""
    digest = F.sha1(payload)
    parts = [F.lpad(F.conv(F.substring(digest, i, 5), 16, 32), 4, "0") for i in range(1, 41, 5)]
    return F.translate(F.concat(*parts), DIGITS32, BASE32)


def resolve(pages: DataFrame, least_bytes: int = LEAST_BYTES) -> DataFrame:
    """page_id, digest, and refers_to: null for a response."""
    payload = F.coalesce("html", F.lit(""))
    headers = pages.select("page_id", sha1_base32(payload).alias("digest"), F.octet_length(payload).alias("size"))
    best = headers.where(F.col("size") >= least_bytes).groupBy("digest").agg(F.max("page_id").alias("best"), F.count("*").alias("n")).where("n > 1").select("digest", "best")
    found = headers.join(best, "digest", "left")
    other = F.col("best").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("best"))
    return found.select("page_id", "digest", F.when(other, F.col("best")).alias("refers_to"))


def records(pages: DataFrame, least_bytes: int = LEAST_BYTES) -> DataFrame:
    """The text of one WARC record per page, without the two line ends that close it."""
    decided = resolve(pages, least_bytes).select(F.col("page_id").alias("_p"), "digest", "refers_to").distinct()
    payload = F.coalesce("html", F.lit(""))
    p = pages.select("page_id", "url", payload.alias("payload")).withColumn("digest", sha1_base32(F.col("payload")))
    p = p.join(decided.withColumnRenamed("digest", "_g"), p["page_id"].eqNullSafe(F.col("_p")) & (p["digest"] == F.col("_g")))
    revisit = F.col("refers_to").isNotNull()
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.octet_length("payload").cast("string"), F.lit(END))
    block = F.when(revisit, http).otherwise(F.concat(http, "payload"))
    name = lambda c: F.concat(F.lit("<urn:x-page:"), F.coalesce(F.col(c).cast("string"), F.lit("null")), F.lit(">"))
    head = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), F.when(revisit, "revisit").otherwise("response"),
        F.lit("\r\nWARC-Record-ID: "), name("page_id"),
        F.lit(f"\r\nWARC-Date: {DATE}\r\nWARC-Target-URI: "), F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]", ""),
        F.lit("\r\nWARC-Payload-Digest: sha1:"), F.col("digest"),
        F.when(revisit, F.concat(F.lit(f"\r\nWARC-Profile: {PROFILE}\r\nWARC-Refers-To: "), name("refers_to"))).otherwise(""),
        F.lit("\r\nContent-Type: application/http; msgtype=response\r\nContent-Length: "), F.octet_length(block).cast("string"), F.lit(END),
    )
    return p.select(F.concat(head, block).alias("value"))


def write_archives(pages: DataFrame, path: str, least_bytes: int = LEAST_BYTES, archive_records: int = ARCHIVE_RECORDS) -> None:
    """Writes all records under `path`, as they are dealt by the join that decided them: no further exchange of the payloads."""
    records(pages, least_bytes).write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", archive_records).text(path)


def parse(raw: bytes, partial: bool = False):
    """(headers, block, end) of every record of an archive; lengths are checked. partial: stops before a record that is not
    whole yet, instead of refusing it."""
    at = 0
    while at < len(raw):
        split = raw.find(b"\r\n\r\n", at)
        if not raw.startswith(b"WARC/", at) or split < 0 and not partial:
            raise ValueError(f"no WARC record at byte {at}")
        if split < 0:
            return
        headers = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in raw[at:split].decode().split("\r\n")[1:])
        end = split + 4 + int(headers["Content-Length"])
        if partial and len(raw) < end + 4:
            return
        if raw[end : end + 4] != b"\r\n\r\n":
            raise ValueError(f"record of byte {at} is cut short")
        yield headers, raw[split + 4 : end], end + 4
        at = end + 4


def _page(uri: str) -> int | None:
    number = uri.rpartition(":")[2].rstrip(">")
    return None if number == "null" else int(number)


def _row(headers: dict, block: bytes, archive: str) -> tuple:
    http, _, payload = block.partition(b"\r\n\r\n")
    size = int(http.rpartition(b"Content-Length: ")[2])
    digest = headers["WARC-Payload-Digest"].removeprefix("sha1:")
    if headers["WARC-Type"] == "response":
        digest, said, size = base64.b32encode(hashlib.sha1(payload).digest()).decode(), digest, len(payload)
        if digest != said:
            raise ValueError(f"payload of {headers['WARC-Record-ID']} does not match its digest")
    refers = headers.get("WARC-Refers-To")
    return _page(headers["WARC-Record-ID"]), size, digest, headers["WARC-Type"], _page(refers) if refers else None, archive


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """Every record: page_id, payload_bytes, payload_digest, record_type, refers_to, archive. The digest of each stored
    payload is computed anew and compared with its header. A compressed file is one split, read from its start to its end:
    its pieces between double line ends are put together again and parsed as they come."""

    def run(batches):
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
        rest, archive = b"", None
        for batch in batches:
            rows = []
            names = batch.column("archive")
            cuts = [0, *(i + 1 for i in np.flatnonzero(pc.not_equal(names[1:], names[:-1]).to_numpy(zero_copy_only=False)).tolist()), len(batch)] if len(batch) else []
            for a, b in zip(cuts[:-1], cuts[1:]):
                if archive != names[a].as_py():
                    if rest:
                        raise ValueError(f"the last record of {archive} is cut short")
                    archive = names[a].as_py()
                raw = b"".join([rest, *(x for piece in batch.column("value")[a:b].cast(pa.binary()).to_pylist() for x in (piece, b"\r\n\r\n"))])
                done = 0
                for headers, block, done in parse(raw, partial=True):
                    rows.append(_row(headers, block, archive))
                rest = raw[done:]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "archive"])
        if rest:
            raise ValueError(f"the last record of {archive} is cut short")

    files = spark.read.option("lineSep", END).option("pathGlobFilter", "*.gz").text(path)
    return files.select("value", F.col("_metadata.file_path").alias("archive")).mapInArrow(run, RECORD)


def round_trip(pages: DataFrame, least_bytes: int = LEAST_BYTES) -> DataFrame:
    """Writes the archives to a folder of their own below the shared one and reads them back."""
    spark = pages.sparkSession
    path = f"{ensure_checkpoint_dir(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    write_archives(pages, path, least_bytes)
    return read_archives(spark, path)


#: DuckDB over the table `pages`.
SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
q AS (SELECT page_id, strlen(body) AS payload_bytes, body, max(page_id) OVER (PARTITION BY body) AS best, sha1(body) AS hex FROM p),
r AS (SELECT *, list_transform(range(0, 8), lambda i: CAST('0x' || substr(hex, CAST(i * 5 + 1 AS INTEGER), 5) AS INTEGER)) AS v FROM q)
SELECT page_id, payload_bytes,
  list_aggregate(list_transform(v, lambda x: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (x >> 15) % 32 + 1, 1) || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (x >> 10) % 32 + 1, 1)
    || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (x >> 5) % 32 + 1, 1) || substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', x % 32 + 1, 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = best THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = best THEN NULL ELSE best END AS refers_to
FROM r
"""
