"""WARC archives: write, read, and resolve revisits.

Archives are gzipped WARC/1.1 files of bounded record counts, written by Spark's text writer (a record
ends with two line ends, which is the writer's separator) and read whole, file by file.

1. Pages become response records with HTTP headers and the payload's SHA-1.
2. Headers alone are read back and shuffled by payload digest. The record with the largest page id of a
   digest is its original; ties go to the larger record id. Maxima are combined before the shuffle, and
   the join back reads written tables on both sides, so a payload with a third of all pages is split.
3. Decisions meet payloads by record id; a new archive is written with fresh headers, where all but the
   originals are revisit records without payload.
4. On reading, each revisit is joined to the response that it refers to.

A null html is an empty payload, which is a payload like others. Payloads of fewer than ``least`` bytes
are never revisits. Null URLs get a URN of the record; page ids may be null (smallest of all) or repeat.
Line ends in URLs are percent-encoded. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm.store import Scratch, table

DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORDS_PER_FILE = 4_000
#: Payload bytes that a file holds on average at most, as files are read whole.
BYTES_PER_FILE = 64 << 20
_HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
_HEADS = "record_id string, record_type string, page_id long, url string, date string, digest string, payload_bytes long, refers_to_record string, refers_to_url string"


def _head(fields: list[tuple[str, str]]) -> bytes:
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields).encode() + b"\r\n"


def response(record_id: str, page_id: int | None, url: str, date: str, digest: str, payload: bytes) -> bytes:
    block = _HTTP % len(payload) + payload
    fields = [("WARC-Type", "response"), ("WARC-Record-ID", f"<{record_id}>"), ("WARC-Target-URI", url), ("WARC-Date", date), ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", str(len(block)))]
    if page_id is not None:
        fields.insert(2, ("X-Page-Id", str(page_id)))
    return _head(fields) + block


def revisit(record_id: str, page_id: int | None, url: str, date: str, digest: str, to_record: str, to_url: str, to_date: str) -> bytes:
    fields = [("WARC-Type", "revisit"), ("WARC-Record-ID", f"<{record_id}>"), ("WARC-Target-URI", url), ("WARC-Date", date), ("WARC-Profile", PROFILE), ("WARC-Payload-Digest", f"sha1:{digest}"), ("WARC-Refers-To", f"<{to_record}>"), ("WARC-Refers-To-Target-URI", to_url), ("WARC-Refers-To-Date", to_date), ("Content-Length", "0")]
    if page_id is not None:
        fields.insert(2, ("X-Page-Id", str(page_id)))
    return _head(fields)


def records(content: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of each record of an archive, gzipped or not."""
    while content[:2] == b"\x1f\x8b":
        one = zlib.decompressobj(31)
        plain = one.decompress(content) + one.flush()
        yield from records(plain)
        content = one.unused_data
    at = 0
    while at < len(content):
        end = content.index(b"\r\n\r\n", at)
        lines = content[at:end].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        fields = dict(line.split(": ", 1) for line in lines[1:])
        begin = end + 4
        stop = begin + int(fields["Content-Length"])
        yield fields, content[begin:stop]
        at = stop + 4


def _first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    part, n = TaskContext.get().partitionId(), 0
    for batch in batches:
        out = []
        for page_id, url, html in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html")), strict=True):
            record_id = uuid.uuid5(uuid.NAMESPACE_URL, f"{page_id}/{part}/{n}").urn
            n += 1
            payload = (html or "").encode()
            digest = base64.b32encode(hashlib.sha1(payload, usedforsecurity=False).digest()).decode()
            url = record_id if url is None else url.replace("\r", "%0D").replace("\n", "%0A")
            out.append(response(record_id, page_id, url, DATE, digest, payload))
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["record"])


def _second(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for r in batch.to_pylist():
            own = (r["record_id"], r["page_id"], r["url"], r["date"], r["digest"])
            out.append(response(*own, r["payload"]) if r["to_record"] is None else revisit(*own, r["to_record"], r["to_url"], r["to_date"]))
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["record"])


def _parsed(payloads: bool):
    kinds = {"record_id": pa.string(), "record_type": pa.string(), "page_id": pa.int64(), "url": pa.string(), "date": pa.string(), "digest": pa.string(), "payload_bytes": pa.int64(), "refers_to_record": pa.string(), "refers_to_url": pa.string()}
    if payloads:
        kinds["payload"] = pa.binary()

    def flush(cols: dict[str, list]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(cols[c], kind) for c, kind in kinds.items()], list(kinds))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content"):
                cols: dict[str, list] = {c: [] for c in kinds}
                size = 0
                for f, block in records(content.as_py()):
                    body = block[block.index(b"\r\n\r\n") + 4 :] if block else b""
                    is_response = f["WARC-Type"] == "response"
                    to = f.get("WARC-Refers-To")
                    values = [f["WARC-Record-ID"][1:-1], f["WARC-Type"], int(f["X-Page-Id"]) if "X-Page-Id" in f else None, f["WARC-Target-URI"], f["WARC-Date"], f["WARC-Payload-Digest"].removeprefix("sha1:"), len(body) if is_response else None, to and to[1:-1], f.get("WARC-Refers-To-Target-URI")]
                    for c, v in zip(kinds, [*values, body] if payloads else values, strict=True):
                        cols[c].append(v)
                    size += len(block)
                    if size > 8 << 20:
                        yield flush(cols)
                        cols, size = {c: [] for c in kinds}, 0
                if cols["record_id"]:
                    yield flush(cols)

    return rows


def records_per_file(n: int | None, total: int | None) -> int:
    """Records of a file, from the number and the payload bytes of all."""
    return max(1, min(RECORDS_PER_FILE, BYTES_PER_FILE * (n or 0) // max(total or 0, 1) or 1)) if total else RECORDS_PER_FILE


def write_archive(rows: DataFrame, path: str, most: int = RECORDS_PER_FILE) -> None:
    """Write the ``record`` column as gzipped archives of ``most`` records."""
    rows.select(F.col("record").cast("string").alias("value")).write.mode("overwrite").option("lineSep", "\r\n\r\n").option("compression", "gzip").option("maxRecordsPerFile", most).text(path)


def read_archive(spark: SparkSession, path: str, payloads: bool = False) -> DataFrame:
    """One row per record: its headers, the length of its payload and, if asked for, the payload."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(_parsed(payloads), _HEADS + (", payload binary" if payloads else ""))


def archive_pages(pages: DataFrame, path: str) -> None:
    n, total = pages.agg(F.count("*"), F.sum(F.octet_length(F.col("html").cast("string")))).first()
    write_archive(pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(_first, "record binary"), path, records_per_file(n, total))


def dedup_archive(spark: SparkSession, source: str, target: str, scratch: Scratch, least: int = 0) -> None:
    """Write ``source`` again to ``target`` with repeated payloads as revisit records."""
    heads = scratch.save(read_archive(spark, source).drop("refers_to_record", "refers_to_url"), "heads")
    counted = heads.where(F.col("payload_bytes") >= least)
    originals = scratch.save(counted.groupBy("digest").agg(F.max(F.struct("page_id", "record_id", "url", "date")).alias("best"), F.count("*").alias("n")).where("n > 1").select("digest", "best"), "originals")
    other = counted.join(originals, "digest").where("record_id <> best.record_id")
    decided = other.select("record_id", F.col("best.record_id").alias("to_record"), F.col("best.url").alias("to_url"), F.col("best.date").alias("to_date"))
    decided = scratch.save(decided, "decided")
    n, total = heads.agg(F.count("*"), F.sum("payload_bytes")).first()
    whole = read_archive(spark, source, payloads=True).drop("refers_to_record", "refers_to_url")
    write_archive(whole.join(decided, "record_id", "left").mapInArrow(_second, "record binary"), target, records_per_file(n, total))


def resolve(spark: SparkSession, path: str, scratch: Scratch) -> DataFrame:
    """Headers of an archive, revisits completed from the responses that they refer to."""
    heads = scratch.save(read_archive(spark, path), "resolved")
    answers = heads.where("record_type = 'response'")
    again = heads.where("record_type = 'revisit'").drop("payload_bytes")
    found = again.join(answers.select(F.col("record_id").alias("refers_to_record"), F.col("page_id").alias("refers_to"), "payload_bytes"), "refers_to_record", "left")
    columns = ["page_id", "payload_bytes", F.col("digest").alias("payload_digest"), "record_type", "refers_to", "record_id", "url"]
    return answers.withColumn("refers_to", F.lit(None).cast("long")).select(*columns).unionByName(found.select(*columns))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "op2")
    archive_pages(table(spark, sf_dir, "pages"), scratch.path("archive"))
    dedup_archive(spark, scratch.path("archive"), scratch.path("deduplicated"), scratch)
    scratch.drop("archive")
    scratch.release()
    return resolve(spark, scratch.path("deduplicated"), scratch).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = r"""
WITH h AS (
  SELECT page_id, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha1(coalesce(html, '')) AS x FROM pages
), b AS (
  SELECT page_id, payload_bytes, array_to_string(list_transform(range(32), lambda i:
    substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (((('0x' || substr(x, (i // 4 * 5 + 1)::INT, 5))::INT >> (15 - 5 * (i % 4))::INT) & 31) + 1)::INT, 1)), '') AS payload_digest FROM h
), m AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS top FROM b)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top THEN top END AS refers_to FROM m
"""
