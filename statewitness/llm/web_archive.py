"""Legacy web archives (ARC, versions 1 and 2) and their conversion to WARC.

An ARC file starts with a version block that names the fields of the one-line headers after it; a
record is a header line, then as many bytes as the header's last field declares, then a line end. The
converter walks by declared lengths alone, so contents may hold anything. Each record becomes a WARC
record with an identifier derived from its page and payload, an ISO timestamp, a type and digests; the
later copies of a payload (all but the one with the largest page id) become ``revisit`` records without
the payload that refer to it.

Archives are written by Spark's text writer with record ends as line separators (so any Hadoop file system
will do) and read as whole files, each of at most ``PER_FILE`` records and, by the longest record, some ``FILE_BYTES``
bytes; every file starts with its own version
block or ``warcinfo`` record. What decides between ``response`` and ``revisit`` is an aggregate of digests;
payloads are not shuffled unless there are more copies than may be broadcast.

Defined results: a page whose id is null is written without a number, is read back with a null id, and revisits a
copy that has one; if no copy has one, all are responses; null html is an empty payload; a null url is written as ``about:blank``, and white space in
one is percent-encoded; rows that repeat the largest page id of a payload are responses each; an empty
table gives no archive and no rows; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from statewitness.llm.arrow_text import column
from statewitness.llm.bounded import BROADCAST_KEYS
from statewitness.llm.scratch import Scratch

PER_FILE = 2000
#: Most bytes of a file, unless one record alone is longer.
FILE_BYTES = 64_000_000
ORIGIN = "statewitness"
# Fixed values of the two formats.
FIELDS_1 = "URL IP-address Archive-date Content-type Archive-length"
FIELDS_2 = "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length"
WARC_VERSION = "WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORD_END = "\r\n\r\n"
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def payload_digest(text: Column) -> Column:
    """Upper-case base 32 SHA-1 of a text in UTF-8, on the JVM: five hex digits give four symbols."""
    hexed = F.sha1(text)
    parts = [F.lpad(F.conv(F.substring(hexed, 1 + 5 * k, 5), 16, 32), 4, "0") for k in range(8)]
    return F.translate(F.upper(F.concat(*parts)), "0123456789ABCDEFGHIJKLMNOPQRSTUV", BASE32)


def sha1_32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


# --- ARC --------------------------------------------------------------------------------------------


def arc_version_block(version: int, name: str, date: str) -> str:
    body = f"{version} 0 {ORIGIN}\n{FIELDS_1 if version == 1 else FIELDS_2}\n"
    head = f"filedesc://{name} 0.0.0.0 {date} text/plain "
    return (head if version == 1 else f"{head}200 - - 0 {name} ") + f"{len(body)}\n{body}"


def page_number(headers: dict[str, str]) -> int | None:
    """The page id in an HTTP header; a page without an id has none there."""
    return int(headers["x-page-id"]) if headers.get("x-page-id") else None


def records_per_file(longest: int | None, limit: int = PER_FILE) -> int:
    """As many records as keep a file within FILE_BYTES if all were as long as the longest payload."""
    return max(1, min(limit, FILE_BYTES // ((longest or 0) + 2000)))


def arc_record(version: int, name: str, url: str | None, date: str, page_id: int | None, html: str) -> str:
    """One record: an HTTP response whose header carries the page id."""
    size = len(html.encode())
    content = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: {size}\r\nX-Page-Id: {'' if page_id is None else page_id}\r\n\r\n"
    total = len(content) + size
    place = re.sub(r"\s", lambda m: "".join(f"%{b:02X}" for b in m[0].encode()), url or "about:blank")
    middle = "" if version == 1 else f"200 {sha1_32(html.encode())} - 0 {name} "
    return f"{place} 0.0.0.0 {date} text/html {middle}{total}\n{content}{html}"


@dataclass
class ArcRecord:
    url: str
    date: str
    content_type: str
    content: bytes
    fields: dict[str, str] = field(default_factory=dict)


def parse_arc(raw: bytes) -> Iterator[ArcRecord]:
    """Records of one ARC file (several ones end to end will do); version blocks name the fields."""
    at, names = 0, None
    while at < len(raw):
        end = raw.find(b"\n", at)
        if end < 0:
            raise ValueError(f"ARC header at byte {at} has no end")
        line = raw[at:end].decode()
        if not line.strip():
            at = end + 1
            continue
        parts = line.split(" ")
        size = int(parts[-1])
        content = raw[end + 1 : end + 1 + size]
        if len(content) < size:
            raise ValueError(f"ARC record at byte {at} declares {size} bytes, {len(content)} are left")
        at = end + 1 + size
        if line.startswith("filedesc://"):
            lines = content.decode().split("\n")
            if lines[0].split(" ")[0] not in ("1", "2"):
                raise ValueError(f"ARC version {lines[0].split(' ')[0]} is not known")
            names = lines[1].split(" ")
            continue
        if names is None:
            raise ValueError("ARC file without a version block")
        if len(parts) < len(names):
            raise ValueError(f"ARC header has {len(parts)} of {len(names)} fields: {line[:200]}")
        # a url with blanks: the fields after it are counted from the end
        values = [" ".join(parts[: len(parts) - len(names) + 1]), *parts[len(parts) - len(names) + 1 :]]
        got = dict(zip(names, values))
        yield ArcRecord(got["URL"], got["Archive-date"], got["Content-type"], content, got)


def http_parts(content: bytes) -> tuple[dict[str, str], bytes, bytes]:
    """(headers in lower case, header block, payload) of an HTTP response."""
    head, _, payload = content.partition(b"\r\n\r\n")
    lines = head.decode("latin-1").split("\r\n")[1:]
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}, head + b"\r\n\r\n", payload


# --- WARC -------------------------------------------------------------------------------------------


def record_id(page_id: int | None, digest: str) -> str:
    """The same page and payload always have the same identifier."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{ORIGIN}:{page_id}:{digest}')}>"


def iso_date(arc_date: str) -> str:
    d = arc_date.ljust(14, "0")
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def warc_record(kind: str, headers: list[tuple[str, str]], block: bytes) -> bytes:
    lines = [WARC_VERSION, f"WARC-Type: {kind}", *(f"{k}: {v}" for k, v in headers), f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block


def warc_info(name: str) -> bytes:
    block = f"software: {ORIGIN}\r\nformat: WARC File Format 1.1\r\n".encode()
    return warc_record("warcinfo", [("WARC-Record-ID", record_id(-1, name)), ("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], block)


def convert(record: ArcRecord, refers_to: int | None) -> bytes:
    """The WARC record of an ARC record; ``refers_to`` is the page that holds the payload, for a revisit."""
    headers, head, payload = http_parts(record.content)
    digest, page = sha1_32(payload), page_number(headers)
    block = record.content if refers_to is None else head
    lines = [
        ("WARC-Record-ID", record_id(page, digest)),
        ("WARC-Date", iso_date(record.date)),
        ("WARC-Target-URI", record.url),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("WARC-Block-Digest", f"sha1:{sha1_32(block)}"),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if refers_to is not None:
        lines += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", record_id(refers_to, digest))]
    return warc_record("response" if refers_to is None else "revisit", lines, block)


def parse_warc(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers in lower case, block) of each record, by declared lengths."""
    at = 0
    while at < len(raw):
        end = raw.find(b"\r\n\r\n", at)
        lines = raw[at : max(end, at)].decode().split("\r\n")
        if end < 0 or not lines[0].startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(headers["content-length"])
        block = raw[end + 4 : end + 4 + size]
        if len(block) < size:
            raise ValueError(f"WARC record at byte {at} declares {size} bytes, {len(block)} are left")
        yield headers, block
        at = end + 4 + size
        if raw[at : at + 4] != b"\r\n\r\n":
            raise ValueError(f"WARC record at byte {at} has no end")
        at += 4


# --- tables -----------------------------------------------------------------------------------------


def unzipped(content: bytes) -> bytes:
    return zlib.decompress(content, 31) if content[:2] == b"\x1f\x8b" else content


def in_files(rows: Iterator[str], opening: Callable[[int], str], per_file: int) -> Iterator[pa.RecordBatch]:
    """Batches of records; each ``per_file`` of them begin with an opening record."""
    out: list[str] = []
    for k, row in enumerate(rows):
        if k % per_file == 0:
            out.append(opening(k // per_file))
        out.append(row)
        if len(out) >= 200:
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string())], names=["value"])
            out = []
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.string())], names=["value"])


def write_records(rows: DataFrame, path: str, end: str, per_file: int) -> None:
    rows.write.option("lineSep", end).option("compression", "gzip").option("maxRecordsPerFile", per_file + 1).text(path)


def read_files(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")


def write_arc(pages: DataFrame, path: str, version: int = 1, date: str = "20240101000000", per_file: int = PER_FILE) -> None:
    """Write pages (page_id, url, html) as ARC files."""
    per_file = records_per_file(pages.agg(F.max(F.octet_length("html"))).first()[0], per_file)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[str]:
            for batch in batches:
                for page, url, html in zip(*(column(batch, c) for c in ("page_id", "url", "html"))):
                    yield arc_record(version, "pages.arc", url.as_py(), date, page.as_py(), html.as_py() or "")

        yield from in_files(rows(), lambda k: arc_version_block(version, f"pages-{k}.arc", date), per_file)

    write_records(pages.select("page_id", "url", "html").mapInArrow(run, "value string"), path, "\n", per_file)


def arc_payloads(spark: SparkSession, path: str) -> DataFrame:
    """page_id, payload_bytes and payload_digest of the records of ARC files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in column(batch, "content"):
                rows = []
                for record in parse_arc(unzipped(content.as_py())):
                    headers, _, payload = http_parts(record.content)
                    rows.append((page_number(headers), len(payload), sha1_32(payload)))
                cols = list(zip(*rows)) or [()] * 3
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.string()))], names=["page_id", "payload_bytes", "payload_digest"])

    return read_files(spark, path).mapInArrow(run, "page_id long, payload_bytes long, payload_digest string")


def revisits(payloads: DataFrame, min_bytes: int = 0) -> DataFrame:
    """(payload_digest, payload_bytes, refers_to): the response's page of each payload that occurs twice or more."""
    groups = payloads.filter(F.col("payload_bytes") >= min_bytes).groupBy("payload_digest", "payload_bytes").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n"))
    return groups.filter("n > 1").drop("n")


def arc_to_warc(spark: SparkSession, arc_path: str, warc_path: str, min_bytes: int = 0, per_file: int = PER_FILE, broadcast_keys: int = BROADCAST_KEYS) -> None:
    """Convert ARC files to WARC files."""
    s = Scratch(spark)
    payloads, most = s.save_seen(arc_payloads(spark, arc_path), "payloads", F.max("payload_bytes").alias("longest"))
    found, seen = s.save_seen(revisits(payloads, min_bytes), "revisits")
    small, per_file = seen["n"] <= broadcast_keys, records_per_file(most["longest"], per_file)
    s.drop("payloads")

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in column(batch, "content"):
                rows: list[tuple] = []
                held = 0
                for r in parse_arc(unzipped(content.as_py())):
                    _, _, payload = http_parts(r.content)
                    rows.append((r.url, r.date, r.content_type, r.content, sha1_32(payload), len(payload)))
                    held += len(r.content)
                    if held > 4_000_000:
                        yield records(rows)
                        rows, held = [], 0
                if rows:
                    yield records(rows)

    def records(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.string(), pa.string(), pa.string(), pa.binary(), pa.string(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=["url", "date", "kind", "content", "payload_digest", "payload_bytes"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[str]:
            for batch in batches:
                cols = [column(batch, c) for c in ("url", "date", "kind", "content", "refers_to")]
                for url, date, kind, content, to in zip(*cols):
                    record = ArcRecord(url.as_py(), date.as_py(), kind.as_py(), content.as_py())
                    page, target = page_number(http_parts(record.content)[0]), to.as_py()
                    yield convert(record, None if target is None or target == page else target).decode()

        yield from in_files(rows(), lambda k: warc_info(f"pages-{k}.warc").decode(), per_file)

    unpacked = read_files(spark, arc_path).mapInArrow(unpack, "url string, date string, kind string, content binary, payload_digest string, payload_bytes long")
    side = F.broadcast(found) if small else found.hint("merge")
    joined = unpacked.join(side, ["payload_digest", "payload_bytes"], "left")
    write_records(joined.select("url", "date", "kind", "content", "refers_to").mapInArrow(pack, "value string"), warc_path, RECORD_END, per_file)
    s.drop("revisits")


READ = "record_id string, page_id long, payload_bytes long, payload_digest string, record_type string, refers_id string"


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """The response and revisit records of WARC files; digests of payloads that are there are recomputed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in column(batch, "content"):
                rows = []
                for headers, block in parse_warc(unzipped(content.as_py())):
                    kind = headers["warc-type"]
                    if kind not in ("response", "revisit"):
                        continue
                    digest = headers["warc-payload-digest"].removeprefix("sha1:")
                    http, _, payload = http_parts(block)
                    size = int(http["content-length"])
                    if kind == "response" and (sha1_32(payload), len(payload)) != (digest, size):
                        raise ValueError(f"payload of {headers['warc-record-id']} does not match its digest")
                    rows.append((headers["warc-record-id"], page_number(http), size, digest, kind, headers.get("warc-refers-to")))
                cols = list(zip(*rows)) or [()] * 6
                kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=[x.split()[0] for x in READ.split(", ")])

    return read_files(spark, path).mapInArrow(run, READ)


def archive_report(pages: DataFrame, min_bytes: int = 0, version: int = 1, per_file: int = PER_FILE) -> DataFrame:
    """Write pages as ARC, convert to WARC, read that back: one row per page."""
    spark = pages.sparkSession
    s = Scratch(spark)
    arc, warc = s.path("arc"), s.path("warc")
    s.paths |= {"arc": arc, "warc": warc}
    write_arc(pages, arc, version, per_file=per_file)
    arc_to_warc(spark, arc, warc, min_bytes, per_file)
    s.drop("arc")
    rows = s.save(read_warc(spark, warc), "rows", keep=True)
    s.drop("warc")
    targets = rows.filter("record_type = 'response'").select(F.col("record_id").alias("refers_id"), F.col("page_id").alias("refers_to")).distinct()
    out = rows.join(targets, "refers_id", "left")
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def query(spark, sf_dir: str) -> DataFrame:
    return archive_report(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"))


ORACLE = r"""
WITH h AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS x FROM pages),
v AS (SELECT page_id, payload_bytes, list_transform(range(8), lambda k: ('0x' || substr(x, 1 + 5 * k, 5))::BIGINT) AS fives FROM h),
d AS (SELECT page_id, payload_bytes, array_to_string(list_transform(fives, lambda n: array_to_string(list_transform([15, 10, 5, 0], lambda b: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (((n >> b) & 31) + 1)::INTEGER, 1)), '')), '') AS payload_digest FROM v),
m AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest, payload_bytes) AS top FROM d)
SELECT page_id, payload_bytes::BIGINT AS payload_bytes, payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top THEN top END AS refers_to FROM m
"""
