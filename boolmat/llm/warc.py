"""WARC archives: pages are written as request, response (or revisit) and metadata records, and read back as captures.

Writing is a DataFrame plan that ends in Spark's own text writer, whose line separator is the blank line that closes a
record, so archives land in any store that Spark can write. Reading takes whole archives, parses them record by record,
and joins the three records of a capture through their concurrent-to identifiers. An archive holds a bounded number of
records and has to stay below 2 GB compressed, the most that one value holds.

Defined cases: a null payload is empty, a null url gives no target header, equal payloads keep one full response (the
largest page_id; rows that tie on it are all responses), a null page_id is smaller than any, rows that are repeated in
all they hold give one capture each, a capture without metadata has no page_id, an empty table gives an archive without records and no captures.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import keyed_join, shared_dir, written

#: Records per archive file: bounds what a reader takes into memory at once.
RECORDS_PER_FILE = 3_000
#: Up to this number of repeated payloads (about 100 bytes each) their table is broadcast; beyond it only frequent ones.
BROADCAST_PAYLOADS = 100_000
CRLF = "\r\n"
#: Fixed value: the profile of revisits with an equal payload.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORD = "record_id string, warc_type string, concurrent_to string, refers_to string, target_uri string, warc_date string, payload_digest string, digest_ok boolean, payload_bytes bigint, fields string, payload binary"


def base32_sha1(text: Column) -> Column:
    """Bare upper-case base32 of the SHA-1 of a string: 4 groups of 40 bits, each turned by conv."""
    digest = F.upper(F.sha1(text))
    groups = [F.lpad(F.conv(F.substring(digest, 10 * k + 1, 10), 16, 32), 8, "0") for k in range(4)]
    return F.translate(F.concat(*groups), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def _urn(kind: str, key: Column) -> Column:
    return F.concat(F.lit("<urn:uuid:"), F.regexp_replace(F.md5(F.concat(F.lit(kind + "/"), key)), "^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5"), F.lit(">"))


def _record(headers: list[tuple[str, Column]], body: Column) -> Column:
    """One record without its closing blank line; a header whose value is null is left out."""
    lines = [F.coalesce(F.concat(F.lit(name + ": "), value, F.lit(CRLF)), F.lit("")) for name, value in headers]
    return F.concat(F.lit("WARC/1.1" + CRLF), *lines, F.lit("Content-Length: "), F.octet_length(body).cast("string"), F.lit(CRLF + CRLF), body)


def page_records(pages: DataFrame, date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """(value): the records of every page as strings."""
    url = F.replace(F.replace(F.col("url"), F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), url.alias("url"), F.coalesce(F.col("html"), F.lit("")).alias("html"))
    rows = rows.withColumn("same", F.sha2("html", 256)).withColumn("digest", base32_sha1(F.col("html")))
    key = lambda page, link, digest: F.concat_ws("|", F.coalesce(page.cast("string"), F.lit("null")), F.coalesce(link, F.lit("null")), digest)
    first = rows.groupBy("same").agg(F.max(F.struct("page_id", "url")).alias("kept"), F.count("*").alias("n")).where("n > 1 AND kept.page_id IS NOT NULL")
    first = written(first, "payloads")
    joined = rows.join(F.broadcast(first), "same", "left") if first.count() <= BROADCAST_PAYLOADS else keyed_join(rows, first, ["same"], "n", "left")
    revisit = F.col("kept").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("kept.page_id"))
    own = key(F.col("page_id"), F.col("url"), F.col("digest"))
    response_id, target = _urn("response", own), F.col("url")
    refers = F.when(revisit, _urn("response", key(F.col("kept.page_id"), F.col("kept.url"), F.col("digest"))))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.octet_length("html").cast("string"), F.lit(CRLF + CRLF))
    when = F.lit(date)
    response = _record([("WARC-Type", F.when(revisit, "revisit").otherwise("response")), ("WARC-Record-ID", response_id), ("WARC-Target-URI", target), ("WARC-Date", when), ("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))), ("WARC-Profile", F.when(revisit, PROFILE)), ("WARC-Refers-To", refers), ("Content-Type", F.lit("application/http; msgtype=response"))], F.concat(http, F.when(revisit, "").otherwise(F.col("html"))))
    request = _record([("WARC-Type", F.lit("request")), ("WARC-Record-ID", _urn("request", own)), ("WARC-Target-URI", target), ("WARC-Date", when), ("WARC-Concurrent-To", response_id), ("Content-Type", F.lit("application/http; msgtype=request"))], F.concat(F.lit("GET "), F.coalesce(target, F.lit("/")), F.lit(f" HTTP/1.1{CRLF}{CRLF}")))
    about = F.concat(F.lit("pageId: "), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.lit(CRLF))
    metadata = _record([("WARC-Type", F.lit("metadata")), ("WARC-Record-ID", _urn("metadata", own)), ("WARC-Target-URI", target), ("WARC-Date", when), ("WARC-Concurrent-To", response_id), ("Content-Type", F.lit("application/warc-fields"))], about)
    return joined.select(F.explode(F.array(request, response, metadata)).alias("value"))


def write_archives(pages: DataFrame, path: str | None = None, records_per_file: int = RECORDS_PER_FILE, date: str = "2024-01-01T00:00:00Z") -> str:
    """Writes gzip-compressed archives in a folder (a new one in the shared folder by default) and returns its path."""
    path = path or f"{shared_dir(pages.sparkSession)}/boolmat-warc-{uuid.uuid4().hex}"
    page_records(pages, date).write.option("lineSep", CRLF + CRLF).option("compression", "gzip").option("maxRecordsPerFile", records_per_file).text(path)
    return path


def parse_archive(stream: io.BufferedIOBase, with_payload: bool) -> Iterator[dict]:
    """The records of one uncompressed archive; raises ValueError where the framing is broken."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError(f"no record starts with {line[:40]!r}")
        headers = {}
        while (line := stream.readline()).strip():
            name, _, value = line.partition(b":")
            headers[name.strip().lower().decode()] = value.strip().decode("utf-8", "replace")
        length = int(headers["content-length"])
        body = stream.read(length)
        if len(body) != length:
            raise ValueError("a record ends early")
        kind = headers.get("warc-type")
        row = {"record_id": headers.get("warc-record-id"), "warc_type": kind, "concurrent_to": headers.get("warc-concurrent-to"), "refers_to": headers.get("warc-refers-to"), "target_uri": headers.get("warc-target-uri"), "warc_date": headers.get("warc-date"), "payload_digest": (headers.get("warc-payload-digest") or "").removeprefix("sha1:") or None, "digest_ok": None, "payload_bytes": None, "fields": None, "payload": None}
        if kind in ("response", "revisit"):
            head, _, payload = body.partition(b"\r\n\r\n")
            row["fields"] = head.decode("utf-8", "replace")
            if kind == "response":
                row["payload_bytes"] = len(payload)
                row["digest_ok"] = row["payload_digest"] == base64.b32encode(hashlib.sha1(payload).digest()).decode()
                row["payload"] = payload if with_payload else None
            else:
                sizes = [x.split(":", 1)[1] for x in row["fields"].splitlines() if x.lower().startswith("content-length:")]
                row["payload_bytes"] = int(sizes[0]) if sizes else None
        else:
            row["fields"] = body.decode("utf-8", "replace")
        yield row


def read_records(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """A row per record of all archives (.gz or plain) in a folder."""
    files = spark.read.format("binaryFile").load(f"{path}/part-*").select("content")
    names = [x.split()[0] for x in RECORD.split(", ")]
    schema = pa.schema([(n, {"bigint": pa.int64(), "boolean": pa.bool_(), "binary": pa.binary()}.get(t, pa.string())) for n, t in (x.split() for x in RECORD.split(", "))])

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                data = content.as_buffer()
                stream = gzip.GzipFile(fileobj=pa.BufferReader(data)) if data[:2].to_pybytes() == b"\x1f\x8b" else io.BufferedReader(pa.BufferReader(data))
                rows, held = [], 0
                for row in parse_archive(io.BufferedReader(stream), with_payload):
                    rows.append(row)
                    held += 500 + (len(row["payload"]) if row["payload"] else 0)
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_pylist(rows, schema)
                        rows, held = [], 0
                yield pa.RecordBatch.from_pylist(rows, schema)

    assert names == schema.names
    return files.mapInArrow(parse, RECORD)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row per capture: (capture_id, response, request, metadata).

    Request and metadata records meet their response or revisit under its identifier: one shuffle. An identifier that
    stands on several equal responses (repeated rows) gives as many rows. Records without a response give none.
    """
    tied = F.when(F.col("warc_type").isin("response", "revisit"), F.col("record_id")).otherwise(F.col("concurrent_to"))
    whole = F.struct(*records.columns)
    is_response = F.col("warc_type").isin("response", "revisit")
    grouped = records.withColumn("capture_id", tied).groupBy("capture_id").agg(
        F.max(F.when(is_response, whole)).alias("response"),
        F.max(F.when(F.col("warc_type") == "request", whole)).alias("request"),
        F.array_distinct(F.collect_list(F.when(F.col("warc_type") == "metadata", F.struct("record_id", "fields")))).alias("metadata"),
        F.count(F.when(is_response, 1)).alias("n"),
    )
    return grouped.where("n > 0").select("capture_id", "response", "request", "metadata", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("copy")).drop("copy")


def page_captures(captures: DataFrame) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to, digest_ok) per capture; refers_to as a page_id."""
    page = F.regexp_extract(F.get("metadata", F.lit(0))["fields"], r"pageId: (-?[0-9]+)", 1)
    rows = captures.select("capture_id", F.when(page != "", page.cast("long")).alias("page_id"), F.col("response.payload_bytes").alias("payload_bytes"), F.col("response.payload_digest").alias("payload_digest"), F.col("response.warc_type").alias("record_type"), F.col("response.refers_to").alias("original"), F.col("response.digest_ok").alias("digest_ok"))
    revisits, kept = rows.where("record_type = 'revisit'"), rows.where("record_type = 'response'")
    asked = revisits.groupBy("original").agg(F.count("*").alias("n"))
    named = kept.groupBy(F.col("capture_id").alias("original")).agg(F.max("page_id").alias("refers_to")).join(asked, "original")
    out = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "digest_ok"]
    return kept.withColumn("refers_to", F.lit(None).cast("long")).select(out).unionAll(keyed_join(revisits, written(named, "originals"), ["original"], "n", "left").select(out))
