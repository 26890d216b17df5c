"""WARC archives: written from page rows, read back and assembled into one nested row per capture.

A capture is three records (request, response or revisit, metadata) tied by WARC-Concurrent-To. Archives are plain,
uncompressed WARC 1.1, so any reader of the format opens them.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from simweave.plans.staging import broadcast_if_small, release, stage

#: The two empty lines after each record; also Spark's line separator when archives are written.
RECORD_END = "\r\n\r\n"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Bytes of payload that an archive file holds at most, unless a single page has more. Pages are written by classes of size: the
#: class of up to SIZES[k] bytes has FILE_BYTES / SIZES[k] captures a file, larger pages a file each.
FILE_BYTES, SIZES = 32 << 20, (16 << 10, 256 << 10, 4 << 20)


def base32_sha1(data: Column) -> Column:
    """Upper-case base32 SHA-1 of a binary column: each 5 bytes are 8 digits of 5 bits."""
    digest = F.sha1(data)
    parts = [F.lpad(F.conv(F.substring(digest, 1 + 10 * k, 10), 16, 32), 8, "0") for k in range(4)]
    return F.translate(F.upper(F.concat(*parts)), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def page_records(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """page_id, uri, payload, payload_bytes, payload_digest, record_type, refers_to and copy of each page.

    Of pages with equal payloads of at least least_bytes, that with the largest page_id is the response and the
    others revisit it; smaller payloads are all responses. Null html is an empty payload, a null url an empty one. Rows that
    repeat a page id and payload are records of their own: copy is 0 for one of them and tells the others apart.
    """
    read = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce("url", F.lit("")).alias("uri"), F.coalesce("html", F.lit("")).cast("binary").alias("payload"))
    read = read.withColumn("payload_bytes", F.octet_length("payload").cast("long")).withColumn("payload_digest", base32_sha1(F.col("payload")))
    per_page = stage(read.groupBy("page_id", "payload_digest", "payload_bytes").agg(F.count(F.lit(1)).alias("n")), "warc-pages")
    twins = per_page.where(F.col("payload_bytes") >= least_bytes).groupBy("payload_digest", "payload_bytes").agg(F.max("page_id").alias("first_id"), F.count(F.lit(1)).alias("n"))
    twins = stage(twins.where("n > 1").drop("n"), "warc-twins")
    copy = F.lit(0).cast("long")
    if per_page.where("n > 1").limit(1).count():
        numbered = stage(read.withColumn("mid", F.monotonically_increasing_id()), "warc-numbered")
        first = numbered.groupBy(F.col("page_id").alias("p"), F.col("payload_digest").alias("d")).agg(F.min("mid").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
        read = numbered.join(broadcast_if_small(stage(first, "warc-copies"), 64), F.col("page_id").eqNullSafe(F.col("p")) & (F.col("payload_digest") == F.col("d")), "left")
        copy = F.when(F.col("mid") > F.col("first"), F.col("mid")).otherwise(copy)
    joined = read.join(broadcast_if_small(twins, 64), ["payload_digest", "payload_bytes"], "left")
    revisit = F.col("first_id").isNotNull() & ~F.col("first_id").eqNullSafe(F.col("page_id"))
    return joined.select(
        "page_id", "uri", "payload", "payload_bytes", "payload_digest",
        F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("first_id")).alias("refers_to"), copy.alias("copy"),
    )


def _record_id(kind: str, page_id: Column, copy: Column) -> Column:
    """A UUID urn that a kind, a page id, a payload and a copy number determine."""
    h = F.md5(F.concat_ws(":", F.lit(kind), F.coalesce(page_id.cast("string"), F.lit("none")), copy.cast("string"), F.col("payload_digest")))
    return F.concat(F.lit("<urn:uuid:"), *(x for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12)) for x in (([F.lit("-")] if a > 1 else []) + [F.substring(h, a, n)])), F.lit(">"))


def _record(kind: str, fields: list[tuple[str, Column]], body: Column, body_bytes: Column) -> Column:
    lines = [F.lit("WARC/1.1\r\nWARC-Type: "), F.lit(kind) if isinstance(kind, str) else kind]
    for name, value in fields:
        lines.append(F.coalesce(F.concat(F.lit(f"\r\n{name}: "), value), F.lit("")))
    return F.concat(*(x.cast("binary") for x in (*lines, F.lit("\r\nContent-Length: "), body_bytes.cast("string"), F.lit(RECORD_END))), body)


def write_archives(records: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z") -> int:
    """Write page_records() as archives under path: request, response or revisit, and metadata record for each page.

    A folder for each class of payload sizes, with files of at most FILE_BYTES of payload (or one page). Returns their number.
    """
    uri, page = F.regexp_replace("uri", "[\\r\\n]", ""), F.col("page_id")
    copy = F.col("copy")
    main, http = _record_id("response", page, copy), F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n").cast("binary")
    request = F.concat(F.lit("GET "), uri, F.lit(" HTTP/1.1\r\n\r\n")).cast("binary")
    facts = F.concat(F.coalesce(F.concat(F.lit("pageId: "), page.cast("string"), F.lit("\r\n")), F.lit("")), F.lit("payloadLength: "), F.col("payload_bytes").cast("string"), F.lit("\r\n")).cast("binary")
    is_revisit = F.col("record_type") == "revisit"
    body = F.when(is_revisit, http).otherwise(F.concat(http, F.col("payload")))
    shared = [("WARC-Target-URI", uri), ("WARC-Date", F.lit(date))]
    built = F.array(
        _record("request", [("WARC-Record-ID", _record_id("request", page, copy)), ("WARC-Concurrent-To", main), *shared, ("Content-Type", F.lit("application/http; msgtype=request"))], request, F.octet_length(request)),
        _record(
            F.col("record_type"),
            [
                ("WARC-Record-ID", main), *shared, ("Content-Type", F.lit("application/http; msgtype=response")),
                ("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))),
                ("WARC-Refers-To", F.when(is_revisit, _record_id("response", F.col("refers_to"), F.lit(0)))),
                ("WARC-Profile", F.when(is_revisit, F.lit(REVISIT_PROFILE))),
            ],
            body, F.octet_length(body),
        ),
        _record("metadata", [("WARC-Record-ID", _record_id("metadata", page, copy)), ("WARC-Concurrent-To", main), *shared, ("Content-Type", F.lit("application/warc-fields"))], facts, F.octet_length(facts)),
    ).cast("array<string>")
    kind = sum((F.when(F.col("payload_bytes") > size, 1).otherwise(0) for size in SIZES), F.lit(0))
    classes = sorted(r[0] for r in records.select(kind.alias("k")).distinct().collect())
    for k in classes:
        captures = max(1, FILE_BYTES // SIZES[k]) if k < len(SIZES) else 1
        records.where(kind == k).select(F.explode(built).alias("value")).write.option("lineSep", RECORD_END).option("maxRecordsPerFile", 3 * captures).text(f"{path}/size-{k}")
    return len(classes)


def parse_archive(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (names in lower case) and block of every record of one archive, by the declared lengths."""
    at = 0
    while (at := data.find(b"WARC/1.", at)) >= 0:
        end = data.index(b"\r\n\r\n", at)
        head = dict(line.split(": ", 1) for line in data[at:end].decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
        head = {k.lower(): v for k, v in head.items()}
        n = int(head["content-length"])
        yield head, data[end + 4 : end + 4 + n]
        at = end + 4 + n


def read_records(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """One row per record of the archives under path; files are read whole, one at a time, so they are written in bounded size
    (Spark takes files of up to 2 GiB).

    record_id, record_type, concurrent_to, refers_to, uri, date, digest (as declared), payload_bytes and payload_sha1 (base32, of
    the bytes read), page_id and declared_bytes (of metadata), payload (null unless with_payload and a response).
    """
    schema = "record_id string, record_type string, concurrent_to string, refers_to string, uri string, date string, digest string, payload_bytes long, payload_sha1 string, page_id long, declared_bytes long, payload binary"

    def parse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for data in batch["content"]:
                rows = []
                for head, block in parse_archive(data):
                    kind = head["warc-type"]
                    facts = dict(x.split(": ", 1) for x in block.decode().split("\r\n") if ": " in x) if kind == "metadata" else {}
                    payload = block.partition(b"\r\n\r\n")[2] if kind == "response" else None
                    rows.append((
                        head.get("warc-record-id"), kind, head.get("warc-concurrent-to"), head.get("warc-refers-to"), head.get("warc-target-uri"), head.get("warc-date"),
                        head.get("warc-payload-digest", "").removeprefix("sha1:") or None, None if payload is None else len(payload),
                        None if payload is None else base64.b32encode(hashlib.sha1(payload).digest()).decode(),
                        int(facts["pageId"]) if "pageId" in facts else None, int(facts["payloadLength"]) if "payloadLength" in facts else None, payload if with_payload else None,
                    ))
                    if len(rows) >= 2000:
                        yield _frame(rows, schema)
                        rows = []
                yield _frame(rows, schema)

    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content").mapInPandas(parse, schema)


def _frame(rows: list[tuple], schema: str) -> pd.DataFrame:
    frame = pd.DataFrame(rows, columns=[x.split()[0] for x in schema.split(", ")], dtype=object)
    return frame.astype({"payload_bytes": "Int64", "page_id": "Int64", "declared_bytes": "Int64"})


def assemble_captures(records: DataFrame) -> DataFrame:
    """One row per capture: capture_id, request, response and metadata as nested structs (null where missing).

    The response or revisit record names the capture; request and metadata join it through WARC-Concurrent-To, directly or by one
    record between (metadata concurrent to the request). Records that lead to no response keep a row of their own.
    """
    main = F.col("record_type").isin("response", "revisit")
    tied = records.where(~main & F.col("concurrent_to").isNotNull()).select(F.col("record_id").alias("concurrent_to"), F.col("concurrent_to").alias("beyond"))
    linked = records.where(~main).join(tied, "concurrent_to", "left")
    keyed = records.where(main).withColumn("capture_id", F.col("record_id")).unionByName(
        linked.withColumn("capture_id", F.coalesce("beyond", "concurrent_to", "record_id")).drop("beyond")
    )
    fields = [c for c in records.columns]
    pick = lambda cond, name: F.max(F.when(cond, F.struct(*fields))).alias(name)
    return keyed.groupBy("capture_id").agg(
        pick(F.col("record_type") == "request", "request"), pick(main, "response"), pick(F.col("record_type") == "metadata", "metadata")
    )


def archive_round_trip(pages: DataFrame, path: str, with_payload: bool = False) -> DataFrame:
    """Write pages as archives under path, read them back and assemble them.

    page_id, uri, payload_bytes, payload_digest, record_type, refers_to (page id of the response that a revisit names) and, with
    payloads, payload. A revisit's length is the one its metadata record declares. Every row of pages is a capture, repeated rows
    and rows with a null id included. An empty table gives an empty result; other columns are not read.
    """
    records = page_records(pages)
    if not write_archives(records, path):
        none = records.select("page_id", "uri", "payload_bytes", "payload_digest", "record_type", "refers_to", *(["payload"] if with_payload else []))
        return none.where(F.lit(False))
    parsed = stage(read_records(pages.sparkSession, path, with_payload), "warc-records")
    captures = assemble_captures(parsed)
    flat = stage(
        captures.select(
            "capture_id", F.col("metadata.page_id").alias("page_id"), F.col("response.uri").alias("uri"), F.coalesce("response.payload_bytes", "metadata.declared_bytes").alias("payload_bytes"),
            F.coalesce("response.payload_sha1", "response.digest").alias("payload_digest"), F.col("response.record_type").alias("record_type"), F.col("response.refers_to").alias("refers"),
            *([F.col("response.payload").alias("payload")] if with_payload else []),
        ),
        "captures",
    )
    release(parsed)
    named = flat.where("refers is not null").select("refers").distinct()
    named = named.join(flat.select(F.col("capture_id").alias("refers"), F.col("page_id").alias("refers_to")), "refers")
    return flat.join(named, "refers", "left").drop("refers", "capture_id")
