"""Web archives: a converter of legacy ARC records to WARC, a WARC sink and a WARC source.

ARC files of version 1 and 2 are parsed by the header lines and declared
lengths that their version block states. Each record gets an equivalent WARC
record: identifier (from its content, so a repeated task writes the same),
timestamp, type and digests. Records are text rows that end in the WARC
terminator, so Spark's own committed writer makes the files, on any file
system, and reruns after lost executors leave no doubles. A row holds a segment
of records, bounded in bytes.

Null html: an empty payload. Null url: "-" in the header line. Null id: no id
header, null when read back. Of equal payloads the one with the largest id is
the response (ties of repeated rows: each such row is a response). Spaces in an
url are written as %20. An empty table gives an empty archive.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, pieces, save, scratch

#: Field names of an ARC header line, by version.
ARC_FIELDS = {
    1: ("url", "ip", "date", "mime", "length"),
    2: ("url", "ip", "date", "mime", "status", "checksum", "location", "offset", "filename", "length"),
}
ARC_TITLE = {1: "URL IP-address Archive-date Content-type Archive-length", 2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length"}
END = b"\r\n\r\n"
#: Equal payloads from this size on are written once.
MIN_REVISIT = 1000
#: A text row of a written file is a segment of records, of at most this many bytes of html (one page may be longer); segments in a file, which one task reads whole.
SEGMENT_BYTES, FILE_SEGMENTS = 4 << 20, 8
#: Digests of repeated payloads up to this number are broadcast.
BROADCAST_DIGESTS = 200_000
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ID_HEADER = "X-Page-Id"


def arc_version_block(version: int = 2, name: str = "pages.arc", date: str = "20240101000000") -> bytes:
    body = f"{version} 0 widthjoin\n{ARC_TITLE[version]}\n".encode()
    head = f"filedesc://{name} 0.0.0.0 {date} text/plain" + ("" if version == 1 else f" 200 - - 0 {name}")
    return f"{head} {len(body)}\n".encode() + body + b"\n"


def arc_record(url: str, body: bytes, date: str, version: int = 2, ip: str = "0.0.0.0", mime: str = "text/html", name: str = "pages.arc") -> bytes:
    url = re.sub(r"[\x00-\x20]", lambda m: f"%{ord(m[0]):02X}", url or "-")
    extra = "" if version == 1 else f" 200 {hashlib.md5(body).hexdigest()} - 0 {name}"
    return f"{url} {ip} {date} {mime}{extra} {len(body)}\n".encode() + body + b"\n"


def parse_arc(data: bytes) -> Iterator[dict]:
    """The records of an ARC file. Its first record, the version block, states how later header lines are read."""
    at, fields = 0, None
    while at < len(data):
        if data[at : at + 1] in b"\r\n":
            at += 1
            continue
        end = data.find(b"\n", at)
        if end < 0:
            raise ValueError("ARC header line without an end")
        line = data[at:end].decode("utf-8", "replace").rstrip("\r")
        parts = line.split(" ")
        if fields is None:
            if not line.startswith("filedesc:"):
                raise ValueError("an ARC file starts with a version block")
            size = int(parts[-1])
            fields = ARC_FIELDS[int(data[end + 1 : end + 1 + size].split(b" ", 1)[0])]
            at = end + 1 + size
            continue
        if len(parts) < len(fields):
            raise ValueError(f"ARC header line with {len(parts)} of {len(fields)} fields: {line[:80]!r}")
        # an url with bare spaces has too many parts: the fixed fields are the last ones
        own = dict(zip(fields[1:], parts[len(parts) - len(fields) + 1 :], strict=True)) | {"url": " ".join(parts[: len(parts) - len(fields) + 1])}
        size = int(own["length"])
        if end + 1 + size > len(data):
            raise ValueError("ARC record shorter than declared")
        yield own | {"block": data[end + 1 : end + 1 + size]}
        at = end + 1 + size


def split_http(block: bytes) -> tuple[bytes, bytes]:
    """HTTP head with its blank line, and payload; a block that is no HTTP message is all payload."""
    if not block.startswith(b"HTTP/"):
        return b"", block
    head, mark, rest = block.partition(END)
    return head + mark, rest


def warc_date(stamp: str) -> str:
    s = (stamp + "00000101000000"[len(stamp) :])[:14]
    return f"{s[:4]}-{s[4:6]}-{s[6:8]}T{s[8:10]}:{s[10:12]}:{s[12:14]}Z"


def record_id(url: str, date: str, tag: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{url} {date} {tag}')}>"


def warc_record(kind: str, url: str, date: str, own_id: str, block: bytes, payload_sha1: str, mime: str, refers_to: str | None = None) -> bytes:
    """Header and block, without the terminator."""
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {own_id}", f"WARC-Date: {date}", f"WARC-Target-URI: {url}",
        f"WARC-Block-Digest: sha1:{hashlib.sha1(block).hexdigest()}", f"WARC-Payload-Digest: sha1:{payload_sha1}",
    ]
    if refers_to is not None:
        head += [f"WARC-Refers-To: {refers_to}", f"WARC-Profile: {REVISIT_PROFILE}"]
    head += [f"Content-Type: {mime}", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + END + block


def parse_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers (names in lower case) and block of each record."""
    at = 0
    while at < len(data):
        end = data.find(END, at)
        if end < 0 or not data.startswith(b"WARC/", at):
            raise ValueError("not a WARC record")
        lines = data[at:end].decode("utf-8", "replace").split("\r\n")
        head = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(head["content-length"])
        yield head, data[end + 4 : end + 4 + size]
        if data[end + 4 + size : end + 8 + size] != END:
            raise ValueError("WARC record without its terminator")
        at = end + 8 + size


def convert(record: dict, tag: str, refers_to: str | None = None) -> bytes:
    """The WARC record equivalent to a parsed ARC record; with refers_to, a revisit that keeps the HTTP head alone."""
    head, payload = split_http(record["block"])
    kind = "response" if head else "resource"
    date, sha1 = warc_date(record["date"]), hashlib.sha1(payload).hexdigest()
    mime = "application/http; msgtype=response" if head else record["mime"]
    own = record_id(record["url"], date, tag)
    if refers_to is not None:
        return warc_record("revisit", record["url"], date, own, head, sha1, mime, refers_to)
    return warc_record(kind, record["url"], date, own, record["block"], sha1, mime)


def http_block(page_id: int | None, body: bytes) -> bytes:
    own = "" if page_id is None else f"{ID_HEADER}: {page_id}\r\n"
    return f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n{own}\r\n".encode() + body


def page_record_id(page_id: int) -> str:
    """Identifier of the record of a page, known without reading that record."""
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_OID, f'page {page_id}')}>"


def pages_to_warc(batches: Iterator[pa.RecordBatch], version: int = 2, date: str = "20240101000000") -> Iterator[pa.RecordBatch]:
    """Pages are laid out as ARC segments, parsed by the converter, and come out as WARC records."""
    for b in pieces(batches, "html", SEGMENT_BYTES):
        rows = b.to_pylist()
        segment = bytearray(arc_version_block(version, date=date))
        for r in rows:
            segment += arc_record(r["url"], http_block(r["page_id"], r["html"].encode()), date, version)
        out = []
        for r, rec in zip(rows, parse_arc(bytes(segment)), strict=True):
            target = None if r["target"] is None else page_record_id(r["target"])
            whole = convert(rec, str(r["page_id"]), target)
            if r["page_id"] is not None:  # revisits name the page's own identifier
                whole = re.sub(rb"WARC-Record-ID: [^\r]*", f"WARC-Record-ID: {page_record_id(r['page_id'])}".encode(), whole, count=1)
            out.append(whole)
        yield pa.RecordBatch.from_arrays([pa.array([END.join(out)] if out else [], pa.binary())], names=["records"])


def revisits(pages: DataFrame, min_bytes: int = MIN_REVISIT) -> DataFrame:
    """pages with target: the page a row revisits, else null.

    Digests are counted by themselves; those that repeat are broadcast, if few, so that html stays where it is, else joined by digest.
    """
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    d = pages.withColumn("sha", F.when(F.length(body) >= min_bytes, F.unhex(F.sha1(body))))
    last = d.filter("sha IS NOT NULL").groupBy("sha").agg(F.max("page_id").alias("last"), F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.col("sha").alias("sha_of"), "last")
    last = save(last)
    if last.count() <= BROADCAST_DIGESTS:
        last = F.broadcast(last)
    else:  # rows without a digest find no partner; a key of their own keeps them from meeting in one task
        d = d.withColumn("sha", F.coalesce("sha", F.encode(F.concat(F.lit("-"), F.coalesce(F.col("page_id").cast("string"), F.col("url"), F.lit(""))), "UTF-8")))
    return d.join(last, d.sha == last.sha_of, "left").select("page_id", "url", "html", F.when(~F.col("page_id").eqNullSafe(F.col("last")), F.col("last")).alias("target"))


def write_warc(pages: DataFrame, path: str, version: int = 2, min_bytes: int = MIN_REVISIT, file_segments: int = FILE_SEGMENTS) -> None:
    """One WARC record a page (page_id, url, html), as .gz files in path."""
    p = revisits(pick(pages, page_id="long", url="string", html="string"), min_bytes)
    segments = p.mapInArrow(lambda it: pages_to_warc(it, version), "records binary")
    segments.select(F.col("records").cast("string").alias("value")).write.option("lineSep", END.decode()).option("compression", "gzip").option("maxRecordsPerFile", file_segments).text(path)


def read_warc(spark, path: str) -> DataFrame:
    """The records of the archives in path: type, id, date, url, digests, HTTP head's page id and length, payload."""
    import gzip

    def parse(batches):
        for b in batches:
            for data in b.column(0):
                raw = data.as_py()
                raw = gzip.decompress(raw) if raw[:2] == b"\x1f\x8b" else raw
                rows = []
                for head, block in parse_warc(raw):
                    http, payload = split_http(block)
                    own = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in http.decode("utf-8", "replace").split("\r\n"))}
                    page, size = own.get(ID_HEADER.lower()), own.get("content-length")
                    revisit = head["warc-type"] == "revisit"
                    sha1 = head["warc-payload-digest"].partition(":")[2]
                    if not revisit and hashlib.sha1(payload).hexdigest() != sha1:
                        raise ValueError(f"payload digest of {head['warc-record-id']} does not match")
                    rows.append((head["warc-type"], head["warc-record-id"], head["warc-date"], head["warc-target-uri"], sha1, head.get("warc-refers-to"), None if page is None else int(page), int(size or 0) if revisit else len(payload), None if revisit else payload))
                cols = zip(*rows, strict=True) if rows else [()] * len(kinds)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=names)

    kinds = [pa.string()] * 6 + [pa.int64()] * 2 + [pa.binary()]
    names = ["record_type", "record_id", "date", "url", "payload_digest", "refers_to_id", "page_id", "payload_bytes", "payload"]
    schema = ", ".join(f"{n} {'long' if t == pa.int64() else 'binary' if t == pa.binary() else 'string'}" for n, t in zip(names, kinds, strict=True))
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(parse, schema)


def round_trip(pages: DataFrame, path: str | None = None) -> DataFrame:
    """Write the archives, read them back, and resolve each revisit to its response's page."""
    spark = pages.sparkSession
    path = path or scratch(spark)
    write_warc(pages, path)
    r = read_warc(spark, path).drop("payload", "url", "date")
    # only revisits are joined, to the few responses that share a digest with one
    again = r.filter("record_type = 'revisit'").select(F.col("refers_to_id").alias("wanted")).distinct()
    owner = r.filter("record_type <> 'revisit'").join(again, F.col("record_id") == F.col("wanted"), "left_semi").select(F.col("record_id").alias("owner_id"), F.col("page_id").alias("owner_page")).dropDuplicates(["owner_id"])
    return r.join(owner, F.col("refers_to_id") == F.col("owner_id"), "left").select("page_id", "payload_bytes", "payload_digest", "record_type", F.col("owner_page").alias("refers_to"))


ORACLE_SQL = f"""
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
d AS (SELECT page_id, octet_length(b)::BIGINT AS payload_bytes, sha1(b) AS payload_digest FROM p),
m AS (SELECT payload_digest, max(page_id) AS last FROM d WHERE payload_bytes >= {MIN_REVISIT} GROUP BY payload_digest)
SELECT d.page_id, d.payload_bytes, d.payload_digest, CASE WHEN m.last <> d.page_id THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN m.last <> d.page_id THEN m.last END AS refers_to
FROM d LEFT JOIN m ON d.payload_digest = m.payload_digest AND d.payload_bytes >= {MIN_REVISIT}
"""
