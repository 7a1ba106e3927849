"""WARC writing, reading and the assembly of transactions.

Writing stays in the JVM: each page becomes a request, a response (or a revisit, if an
earlier page has the same payload) and a metadata record, written as text whose
separator is the blank lines that end a record; archives are gzip files of at most
``records_per_archive`` captures' records, so a reader's memory is bounded.
Reading parses any such archive, or one with a gzip member for each record, by its
Content-Length fields. Assembly joins request and metadata records to the response or
revisit that they name in WARC-Concurrent-To, and a revisit to the response it refers to,
and gives one nested row for each capture.

Defined results: a null html is an empty payload; equal payloads (empty ones too) have
one response, that of the least page id (of repeated rows, of one of them); repeated rows
are captures of their own; a request or metadata record that names no capture is left
out, of several the one of least record id is taken; an empty table gives no captures; other
columns are ignored.
"""

from __future__ import annotations

import gzip
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.stages import cut, fresh_path

BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
END = "\r\n\r\n"


def base32_sha1(data: Column) -> Column:
    """SHA-1 in upper-case base 32 (32 characters, no padding)."""
    digits = F.sha1(data)
    out = []
    for part in range(8):  # 20 bits each
        n = F.conv(F.substring(digits, part * 5 + 1, 5), 16, 10).cast("int")
        out += [F.substr(F.lit(BASE32), F.shiftright(n, s).bitwiseAND(31) + 1, F.lit(1)) for s in (15, 10, 5, 0)]
    return F.concat(*out)


def archive_pages(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", date: str = "2020-01-01T00:00:00Z", records_per_archive: int = 6_000, archive_bytes: int = 64 << 20) -> None:
    """Write archives with three records for each page, of about ``archive_bytes`` of payload at most by the mean page.

    Rows get their numbers in a table of their own, so a capture keeps its name however often it is read.
    """
    payload = F.coalesce(F.col(html_col), F.lit(""))
    rows = pages.select(
        F.col(id_col).alias("_id"),
        F.regexp_replace(F.coalesce(F.col(url_col), F.lit("urn:none")), r"[\r\n]", "").alias("_url"),
        payload.alias("_body"),
        F.unhex(F.sha1(F.encode(payload, "UTF-8"))).alias("_sha"),
        F.monotonically_increasing_id().alias("_row"),
    )
    rows = cut(rows, "numbered")
    mean = rows.agg(F.avg(F.octet_length("_body"))).first()[0] or 0.0
    many = max(1, min(records_per_archive // 3, int(archive_bytes / max(mean, 1.0))))
    groups = rows.groupBy("_sha").agg(F.count("*").alias("_n"), F.min(F.struct("_id", "_row")).alias("_first"))
    copies = cut(groups.where("_n > 1").select("_sha", "_first"), "copies")
    rows = rows.join(copies, "_sha", "left")
    key = F.concat(F.coalesce(F.col("_id").cast("string"), F.lit("none")), F.lit("-"), F.col("_row").cast("string"))
    first = F.concat(F.coalesce(F.col("_first._id").cast("string"), F.lit("none")), F.lit("-"), F.col("_first._row").cast("string"))
    rows = rows.withColumn("_key", key).withColumn("_again", F.col("_first").isNotNull() & (first != key)).withColumn("_to", first)
    digest = base32_sha1(F.encode("_body", "UTF-8"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.octet_length("_body").cast("string"), F.lit(END))
    urn = lambda kind, k: F.concat(F.lit(f"<urn:capture:{kind}:"), k, F.lit(">"))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))

    def record(kind: Column, name: Column, fields: list[Column], mime: str, block: Column) -> Column:
        return F.concat(
            F.lit("WARC/1.0\r\n"), line("WARC-Type", kind), line("WARC-Record-ID", name), line("WARC-Date", F.lit(date)), *fields,
            line("Content-Type", F.lit(mime)), line("Content-Length", F.octet_length(block).cast("string")), F.lit("\r\n"), block,
        )

    capture = urn("response", F.col("_key"))
    target = line("WARC-Target-URI", F.col("_url"))
    profile = F.lit("http://netpreserve.org/warc/1.0/revisit/identical-payload-digest")
    seen = F.when(F.col("_again"), F.concat(line("WARC-Refers-To", urn("response", F.col("_to"))), line("WARC-Profile", profile))).otherwise(F.lit(""))
    main = record(F.when(F.col("_again"), F.lit("revisit")).otherwise(F.lit("response")), capture, [target, line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), digest)), seen], "application/http;msgtype=response", F.when(F.col("_again"), http).otherwise(F.concat(http, F.col("_body"))))
    asked = record(F.lit("request"), urn("request", F.col("_key")), [target, line("WARC-Concurrent-To", capture)], "application/http;msgtype=request", F.concat(F.lit("GET "), F.col("_url"), F.lit(" HTTP/1.1" + END)))
    about = record(F.lit("metadata"), urn("metadata", F.col("_key")), [line("WARC-Concurrent-To", capture)], "application/warc-fields", line("pageId", F.coalesce(F.col("_id").cast("string"), F.lit(""))))
    out = rows.select(F.concat(asked, F.lit(END), main, F.lit(END), about).alias("value"))
    out.write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", many).text(path)


def _unpack(data: bytes) -> bytes:
    if data[:2] != b"\x1f\x8b":
        return data
    try:
        return gzip.decompress(data)  # every member
    except (EOFError, zlib.error) as e:
        raise ValueError("a truncated or damaged archive") from e


def parse_archive(data: bytes) -> Iterator[tuple[dict[str, str], memoryview]]:
    """(header fields by lower-case name, block) of each record."""
    view, at, size = memoryview(data), 0, len(data)
    while True:
        while at < size and data[at] in b"\r\n":
            at += 1
        if at >= size:
            return
        end = data.find(b"\r\n\r\n", at)
        if not data.startswith(b"WARC/", at) or end < 0:
            raise ValueError(f"no record at byte {at}")
        fields: dict[str, str] = {}
        name = None
        for raw in data[at:end].split(b"\r\n")[1:]:
            text = raw.decode("utf-8", "replace")
            if text[:1] in " \t" and name:
                fields[name] += " " + text.strip()
                continue
            name, _, value = text.partition(":")
            name = name.strip().lower()
            fields[name] = value.strip()
        start = end + 4
        at = start + int(fields.get("content-length", "0"))
        if at > size:
            raise ValueError("a record is longer than its archive")
        yield fields, view[start:at]


def _http_payload(fields: dict[str, str], block: memoryview) -> tuple[bytes, int | None]:
    """(payload, length that the HTTP header gives) of an HTTP block."""
    raw = bytes(block)
    head, gap, body = raw.partition(b"\r\n\r\n")
    length = None
    for h in head.split(b"\r\n")[1:]:
        name, _, value = h.partition(b":")
        if name.strip().lower() == b"content-length" and value.strip().isdigit():
            length = int(value)
    return (body if gap else b""), length


RECORD = "record_id string, type string, date string, target_uri string, concurrent_to string, refers_to string, payload_digest string, declared_digest string, payload_bytes long, payload binary, fields map<string,string>"


def read_archives(spark: SparkSession, path: str, pattern: str = "*") -> DataFrame:
    """One row a record. For responses the digest and length are of the payload read; for
    revisits they are those declared, as their payload is elsewhere."""

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import base64
        import hashlib

        names = [x.split(" ")[0] for x in RECORD.split(", ")]
        for b in batches:
            for data in b["content"]:
                rows, held = [], 0
                for f, block in parse_archive(_unpack(bytes(data))):
                    kind, payload, size, digest, inner = f.get("warc-type", ""), None, None, None, {}
                    declared = f.get("warc-payload-digest", "").removeprefix("sha1:") or None
                    if kind == "response":
                        payload, _ = _http_payload(f, block) if "http" in f.get("content-type", "http") else (bytes(block), None)
                        size, digest = len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode()
                    elif kind == "revisit":
                        _, size = _http_payload(f, block)
                        digest = declared
                    elif f.get("content-type", "").startswith("application/warc-fields"):
                        for text in bytes(block).decode("utf-8", "replace").splitlines():
                            name, gap, value = text.partition(":")
                            if gap:
                                inner[name.strip()] = value.strip()
                    rows.append((f.get("warc-record-id"), kind, f.get("warc-date"), f.get("warc-target-uri"), f.get("warc-concurrent-to"), f.get("warc-refers-to"), digest, declared, size, payload, inner))
                    held += len(block)
                    if held > 4 << 20 or len(rows) >= 5_000:
                        yield pd.DataFrame(rows, columns=names)
                        rows, held = [], 0
                if rows:
                    yield pd.DataFrame(rows, columns=names)

    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path).select("content")
    return files.mapInPandas(scan, RECORD)


def assemble(records: DataFrame) -> DataFrame:
    """One nested row a capture: its response or revisit, request, metadata and referred response."""
    main = records.where(F.col("type").isin("response", "revisit"))
    told = records.where(F.col("type").isin("request", "metadata") & F.col("concurrent_to").isNotNull())
    told = told.groupBy(F.col("concurrent_to").alias("_of")).agg(
        F.min(F.when(F.col("type") == "request", F.struct("record_id", "target_uri", "date"))).alias("request"),
        F.min_by(F.when(F.col("type") == "metadata", F.struct("record_id", "fields")), F.when(F.col("type") == "metadata", F.col("record_id"))).alias("metadata"),
    )
    joined = main.join(told, F.col("record_id") == F.col("_of"), "left")
    return joined.select("record_id", F.struct("type", "date", "target_uri", "payload_digest", "declared_digest", "payload_bytes", "refers_to", "payload").alias("response"), "request", "metadata")


def round_trip(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Write, read back, assemble; digest columns for each page."""
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    archive_pages(pages, path, id_col, url_col, html_col)
    kind = dict(pages.dtypes)[id_col]
    # parsed once; digests and lengths of the payloads read are columns, so the payloads need not be kept
    records = cut(read_archives(spark, path).withColumn("payload", F.lit(None).cast("binary")), "records")
    captures = assemble(records)
    flat = cut(
        captures.select(
            "record_id",
            F.expr(f"cast(nullif(metadata.fields['pageId'], '') as {kind})").alias("_id"),
            F.col("response.type").alias("_type"),
            F.col("response.payload_digest").alias("_digest"),
            F.col("response.payload_bytes").alias("_bytes"),
            F.col("response.refers_to").alias("_to"),
        ),
        "captures",
    )
    first = flat.where("_type = 'response'").select(F.col("record_id").alias("_to"), F.col("_id").alias("_page"))
    out = flat.join(first.join(flat.where("_to is not null").select("_to").distinct(), "_to", "left_semi"), "_to", "left")
    return out.select(F.col("_id").alias(id_col), F.col("_bytes").alias("payload_bytes"), F.col("_digest").alias("payload_digest"), F.col("_type").alias("record_type"), F.when(F.col("_type") == "revisit", F.col("_page")).alias("refers_to"))
