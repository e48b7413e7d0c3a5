"""Legacy archive converter: ARC records (version 1 and 2) to WARC 1.1, writing and reading back.

An ARC file opens with a version block whose text names the fields of every later header line; each
record is a header line, then as many bytes as its last field declares, then a line feed. The
converter parses both layouts by that definition and synthesises what WARC asks for and ARC lacks:
record identifiers (stable, from the row's id), ISO timestamps, record types, block and payload
digests, and revisits for payloads that another record holds.

Archives are written by Spark's text sink: a record's two closing line breaks are the sink's row
separator, so files are plain .warc content in any store Spark can write. They are read as binary files
and cut by their declared lengths.

Defined cases: a null html is an empty payload; a null url becomes urn:absent, white space and control
characters in urls are percent-encoded; null page ids are allowed (the smallest id); rows that repeat a
page_id each get a record, and where their payload is kept under that id all are responses; other
columns are ignored; an empty table writes no record. Payloads below MIN_REVISIT bytes are never revisits.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from markerpanel.llm.common import NULL_ID, arrow_map, keyed, shared_dir, strings, table

MIN_REVISIT = 1000
#: Rows of a file, so that a file fits a reader's memory.
FILE_ROWS = 2000
#: Revisits known up to this many rows are broadcast (40 bytes each); more are joined by shuffle.
BROADCAST_ROWS = 500_000
#: The field lines of the two ARC versions.
ARC_FIELDS = {
    1: "URL IP-address Archive-date Content-type Archive-length",
    2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length",
}
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
SPACE_RUNS = re.compile(r"[\x00-\x20\x7f]")


# -- ARC ------------------------------------------------------------------------------------------
def arc_version_block(version: int, name: str = "pages.arc", date: str = "20240101000000") -> bytes:
    text = f"{version} 0 markerpanel\n{ARC_FIELDS[version]}\n".encode()
    head = f"filedesc://{name} 0.0.0.0 {date} text/plain " + ("" if version == 1 else f"200 - - 0 {name} ") + f"{len(text)}\n"
    return head.encode() + text + b"\n"


def arc_record(version: int, url: str | None, body: bytes, date: str = "20240101000000", mime: str = "text/html", ip: str = "0.0.0.0", offset: int = 0) -> bytes:
    safe = "urn:absent" if not url else SPACE_RUNS.sub(lambda m: f"%{ord(m.group()):02X}", url)
    middle = "" if version == 1 else f"200 - - {offset} pages.arc "
    return f"{safe} {ip} {date} {mime} {middle}{len(body)}\n".encode("utf-8", "replace") + body + b"\n"


def parse_arc(data: bytes) -> Iterator[dict]:
    """Records of an ARC stream after its version block: fields by name, and ``body``."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    end = data.index(b"\n")
    size = int(data[:end].rsplit(b" ", 1)[1])
    block = data[end + 1 : end + 1 + size].decode().split("\n")
    version, fields = int(block[0].split(" ")[0]), block[1].split(" ")
    if fields != ARC_FIELDS.get(version, "").split(" "):
        raise ValueError(f"unknown ARC version block {block[:2]}")
    at = end + 1 + size
    while at < len(data):
        if data[at : at + 1] == b"\n":  # between records
            at += 1
            continue
        end = data.index(b"\n", at)
        values = data[at:end].decode("utf-8", "replace").rsplit(" ", len(fields) - 1)
        if len(values) != len(fields):
            raise ValueError(f"header line has {len(values)} of {len(fields)} fields")
        size = int(values[-1])
        if end + 1 + size > len(data):
            raise ValueError("a declared length runs beyond the archive")
        yield dict(zip(fields, values, strict=True)) | {"version": version, "body": data[end + 1 : end + 1 + size]}
        at = end + 1 + size


# -- WARC -----------------------------------------------------------------------------------------
def record_id(row: int) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page {row}')}>"


def _digest(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def iso_date(arc_date: str) -> str:
    """14 digits (or fewer, read as the first moment of what they name) to an ISO timestamp."""
    d = arc_date + "00000101000000"[len(arc_date) :]
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def to_warc(arc: dict, row: int, refers_to: int | None) -> bytes:
    """A WARC record without the two closing line breaks."""
    http, gap, payload = arc["body"].partition(b"\r\n\r\n")
    if not gap:  # a protocol without a head
        http, payload = b"HTTP/1.0 200 OK", arc["body"]
    block = http + b"\r\n\r\n" + (payload if refers_to is None else b"")
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: {record_id(row)}",
        f"WARC-Date: {iso_date(arc['Archive-date'])}",
        f"WARC-Target-URI: {arc['URL']}",
        f"WARC-IP-Address: {arc['IP-address']}",
        f"WARC-Payload-Digest: {_digest(payload)}",
        f"WARC-Block-Digest: {_digest(block)}",
        "Content-Type: application/http; msgtype=response",
        f"X-Row: {row}",
        f"X-Payload-Length: {len(payload)}",
    ]
    if refers_to is not None:
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"WARC-Refers-To: {record_id(refers_to)}", f"X-Refers-To-Row: {refers_to}"]
    head.append(f"Content-Length: {len(block)}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block


def parse_warc(data: bytes) -> Iterator[tuple[dict, bytes]]:
    """(headers, block) of every record; plain or gzip, also with a member per record."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    at = 0
    while at < len(data):
        if not data.startswith(b"WARC/", at):
            raise ValueError("no record where one should begin")
        end = data.index(b"\r\n\r\n", at)
        head = dict(line.split(": ", 1) for line in data[at:end].decode().split("\r\n")[1:])
        start = end + 4
        stop = start + int(head["Content-Length"])
        if data[stop : stop + 4] != b"\r\n\r\n":
            raise ValueError("a record doesn't end where its length says")
        yield head, data[start:stop]
        at = stop + 4


# -- tables ---------------------------------------------------------------------------------------
def convert_pages(pages: DataFrame, version: int = 1) -> DataFrame:
    """Row by row: page to ARC record to WARC record, as one text column ``record``.

    Of equal payloads of at least MIN_REVISIT bytes the largest page_id keeps the payload. Only digests
    and ids are grouped, combined before the shuffle, so a payload of a third of all pages is one row.
    """
    df = keyed(pages, "url", F.coalesce("html", F.lit("")).alias("html"), key="page_id")
    large = df.filter(F.octet_length("html") >= MIN_REVISIT).select(F.sha1("html").alias("digest"), "page_id")
    kept = large.groupBy("digest").agg(F.max("page_id").alias("keeper"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("digest", "keeper")
    kept = kept.persist()
    small = kept.count() <= BROADCAST_ROWS
    key = F.when(F.octet_length("html") >= MIN_REVISIT, F.sha1("html"))
    df = df.withColumn("digest", key).join(F.broadcast(kept) if small else kept, "digest", "left")
    df = df.select("page_id", "url", "html", F.when(F.col("keeper") != F.col("page_id"), F.col("keeper")).alias("refers_to"))

    def make():
        opening = arc_version_block(version)

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            out = []
            for row, url, html, other in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strings(batch.column(2)), batch.column(3).to_pylist(), strict=True):
                payload = html.as_py()
                http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
                (arc,) = parse_arc(opening + arc_record(version, url, http + payload))
                out.append(to_warc(arc, row, other))
                if len(out) >= 200:
                    yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary()).cast(pa.string())], names=["record"])
                    out = []
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary()).cast(pa.string())], names=["record"])

        return step

    return arrow_map(df, make, "record string")


def write_archives(records: DataFrame, path: str, compression: str = "none") -> None:
    records.write.option("lineSep", "\r\n\r\n").option("compression", compression).option("maxRecordsPerFile", FILE_ROWS).text(path)


READ = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, target_uri string, date string, record_id string, payload binary"


def read_archives(spark: SparkSession, path: str, payloads: bool = True) -> DataFrame:
    """One row per record; the payload of a response is checked against its digest."""
    files = spark.read.format("binaryFile").load(path).select("content")

    def make():
        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for k in range(batch.num_rows):
                rows = []
                for head, block in parse_warc(batch.column(0)[k].as_py()):
                    payload = block.partition(b"\r\n\r\n")[2]
                    digest = base64.b32decode(head["WARC-Payload-Digest"].partition(":")[2])
                    kind = head["WARC-Type"]
                    if kind == "response" and (hashlib.sha1(payload).digest() != digest or len(payload) != int(head["X-Payload-Length"])):
                        raise ValueError(f"payload of {head['WARC-Record-ID']} differs from its digest")
                    other = head.get("X-Refers-To-Row")
                    rows.append((int(head["X-Row"]), int(head["X-Payload-Length"]), digest.hex(), kind, None if other is None else int(other), head["WARC-Target-URI"], head["WARC-Date"], head["WARC-Record-ID"], payload if payloads and kind == "response" else None))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), TYPES, strict=True)], names=NAMES)

        return step

    out = arrow_map(files, make, READ)
    return out.withColumns({c: F.nullif(F.col(c), F.lit(NULL_ID)) for c in ("page_id",)})


TYPES = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.binary()]
NAMES = [f.split(" ")[0] for f in READ.split(", ")]


def op3(spark, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/warc"
    write_archives(convert_pages(table(spark, sf_dir, "pages").select("page_id", "url", "html")), path)
    return read_archives(spark, path, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP3_SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
q AS (SELECT page_id, CAST(octet_length(b) AS BIGINT) AS n, sha1(b) AS d FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY d) AS keeper FROM q)
SELECT page_id, n AS payload_bytes, d AS payload_digest,
       CASE WHEN n >= 1000 AND keeper <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND keeper <> page_id THEN keeper END AS refers_to FROM m
"""
