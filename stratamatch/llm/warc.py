"""WARC archives: a writer for tables of pages and a reader that salvages damaged files.

Writing. Pages are grouped by payload digest with a partial minimum (a payload that
a third of all pages share is one row there); records become gzip members, and
bounded runs of members become the rows of Spark's text sink, which writes them
byte for byte, so files go through Hadoop's file systems and the commit protocol
like any output. The row separator is an empty gzip member.

Reading. Files are read whole (they are bounded), gzip members or plain records
alike. A record counts if its version line, length and block digest (hexadecimal or
base 32) hold. After a failed check the reader looks for the next member or version
line that begins a valid record, goes on there, and reports the bytes between as a
row of kind ``gap``. It does the same inside a member that holds several records:
content lost there is a row of kind ``inner-gap`` with the member's offset and the
number of content bytes. A member that is cut off or fails its checksum gives the
valid records of what can be decompressed, and is a gap itself. Lengths of records
and gaps add up to the file's (records that share a member: the first has its length).

Defined results: null html is an empty payload; payloads under ``least`` bytes are
always responses; of equal payloads with one null id each, the non-null smallest id
is the response; if all ids are null, all are responses; rows that repeat the
response's id are responses as well.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .durable import new_folder, stored
from .wordhash import portions

LEAST, SEGMENT, PER_FILE, BROADCAST_ROWS = 100, 2 << 20, 6, 200_000
_LEVEL = 5


def _member(data: bytes) -> bytes:
    z = zlib.compressobj(_LEVEL, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def record_bytes(page_id, url, payload: bytes, digest: str, refers_to) -> bytes:
    """One WARC record: a response with its payload, or a revisit with HTTP headers only."""
    kind = "response" if refers_to is None else "revisit"
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    url = "".join(c if 32 < ord(c) < 127 else "".join(f"%{b:02X}" for b in c.encode("utf-8", "surrogatepass")) for c in url or "")
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id} {url}')}>", "WARC-Date: 2024-01-01T00:00:00Z", f"WARC-Target-URI: {url}",
        "Content-Type: application/http; msgtype=response", f"WARC-Payload-Digest: sha256:{digest}", f"WARC-Block-Digest: sha1:{hashlib.sha1(block).hexdigest()}", f"Content-Length: {len(block)}",
    ]
    if page_id is not None:
        head.append(f"X-Page-Id: {page_id}")
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"X-Refers-To-Page-Id: {refers_to}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def write_warc(pages: DataFrame, path: str, least: int = LEAST) -> None:
    """Write one record for each row of ``pages`` (page_id, url, html) under ``path``."""
    html = F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), html.alias("payload"))
    rows = rows.withColumn("digest", F.sha2("payload", 256))
    first = rows.where(F.octet_length("payload") >= least).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").select("digest", "first")
    first = stored(first, "first-pages")
    # Payloads stay where they are, unless very many of them repeat.
    rows = rows.join(F.broadcast(first) if first.count() <= BROADCAST_ROWS else first, "digest", "left").withColumn("refers_to", F.when((F.col("first") != F.col("page_id")) | F.col("page_id").isNull(), F.col("first")))
    packed = rows.select("page_id", "url", "payload", "digest", "refers_to").mapInArrow(_segments, "segment binary")
    # Latin-1 keeps the separator's bytes: an empty gzip member.
    packed.select(F.col("segment").cast("string").alias("value")).write.option("encoding", "ISO-8859-1").option("lineSep", _member(b"").decode("latin-1")).option(
        "maxRecordsPerFile", PER_FILE
    ).text(path)


def _segments(batches):
    run, size = [], 0
    for batch in portions(batches, "payload"):
        ids, urls, payloads, digests, refers = (c.to_pylist() for c in batch.columns)
        for row in zip(ids, urls, payloads, digests, refers):
            run.append(_member(record_bytes(*row)))
            size += len(run[-1])
            if size >= SEGMENT:
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(run)], type=pa.binary())], names=["segment"])
                run, size = [], 0
    if run:
        yield pa.RecordBatch.from_arrays([pa.array([b"".join(run)], type=pa.binary())], names=["segment"])


def parse_record(data: bytes, at: int = 0):
    """(headers, block, end) of a valid plain record at ``at``; None if a check fails."""
    if not data.startswith((b"WARC/1.0\r\n", b"WARC/1.1\r\n", b"WARC/0.1"), at):
        return None
    end = data.find(b"\r\n\r\n", at)
    if end < 0:
        return None
    headers = {}
    for line in data[at:end].split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            return None
        headers[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
    try:
        length = int(headers["content-length"])
    except (KeyError, ValueError):
        return None
    begin = end + 4
    block = data[begin : begin + length]
    if length < 0 or len(block) < length or data[begin + length : begin + length + 4] != b"\r\n\r\n":
        return None
    method, _, value = headers.get("warc-block-digest", "").partition(":")
    if method.lower() in ("sha1", "sha256", "md5"):
        own = hashlib.new(method.lower(), block).digest()
        if value.lower() != own.hex() and value.upper().rstrip("=") != base64.b32encode(own).decode().rstrip("="):
            return None
    return headers, block, begin + length + 4


def _content(data: bytes, at: int):
    """(content, end, whole) of the gzip member at ``at``: as much as can be decompressed; ``whole``
    says that it ends and its checksum holds."""
    z, parts, p = zlib.decompressobj(31), [], at
    try:
        while not z.eof and p < len(data):
            parts.append(z.decompress(data[p : p + 4096]))
            p += 4096
    except zlib.error:
        return b"".join(parts), len(data), False
    return b"".join(parts), min(p, len(data)) - len(z.unused_data), z.eof


def _plain(data: bytes):
    """('record', headers, block) and ('gap', bytes lost, None) of plain records."""
    at, bad = 0, None
    while at < len(data):
        got = parse_record(data, at)
        if got is None:
            bad = at if bad is None else bad
            found = data.find(b"WARC/", at + 1)
            at = found if found >= 0 else len(data)
            continue
        if bad is not None:
            yield "gap", at - bad, None
            bad = None
        yield "record", got[0], got[1]
        at = got[2]
    if bad is not None:
        yield "gap", len(data) - bad, None


def _at(data: bytes, at: int):
    """(list of rows as ``_plain``, end, whole) of what begins at ``at``; None if nothing valid does."""
    if data.startswith(b"\x1f\x8b\x08", at):
        content, end, whole = _content(data, at)
        rows = list(_plain(content))
        if not whole:
            rows = [r for r in rows if r[0] == "record"]
        return (rows, end, whole) if whole and not content or any(r[0] == "record" for r in rows) else None
    got = parse_record(data, at)
    return None if got is None else ([("record", got[0], got[1])], got[2], True)


def salvage(data: bytes):
    """('record', offset, length, headers, block) of every valid record, ('gap', offset, length, None,
    None) of the bytes between, ('inner-gap', offset, length, None, None) of content lost in a member."""
    at, bad = 0, None
    while at < len(data):
        got = _at(data, at)
        if got is not None and (got[0] or bad is None):
            rows, end, whole = got
            if whole and bad is not None:
                yield "gap", bad, at - bad, None, None
                bad = None
            length = end - at if whole else 0
            for kind, a, b in rows:
                if kind == "record":
                    yield "record", at, length, a, b
                    length = 0
                else:
                    yield "inner-gap", at, a, None, None
            if whole:
                at = end
                continue
        if bad is None:
            bad = at
        marks = [p for p in (data.find(b"\x1f\x8b\x08", at + 1), data.find(b"WARC/", at + 1)) if p >= 0]
        at = min(marks, default=len(data))
    if bad is not None:
        yield "gap", bad, len(data) - bad, None, None


_SCHEMA = pa.schema([
    ("file", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("kind", pa.string()), ("record_type", pa.string()), ("record_id", pa.string()), ("target_uri", pa.string()),
    ("page_id", pa.int64()), ("refers_to", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("digest_holds", pa.bool_()), ("payload", pa.binary()),
])
_DDL = "file string, offset long, length long, kind string, record_type string, record_id string, target_uri string, page_id long, refers_to long, payload_bytes long, payload_digest string, digest_holds boolean, payload binary"


def read_warc(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """A row for each record and each quarantined gap of the files under ``path``.
    payload_bytes and payload_digest are those of the full payload, also for a revisit;
    digest_holds says whether a response's payload has the digest that it states."""

    def run(batches):
        for batch in batches:
            for name, i in zip(batch.column(0).to_pylist(), range(batch.num_rows)):
                rows, size = [], 0
                for row in _rows(name, batch.column(1)[i].as_py() or b"", with_payload):
                    rows.append(row)
                    size += len(row[-1] or b"") + 300
                    if size > 4 << 20:
                        yield _batch(rows)
                        rows, size = [], 0
                if rows:
                    yield _batch(rows)

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, _DDL)


def _batch(rows):
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), _SCHEMA)], schema=_SCHEMA)


def _number(text):
    return int(text) if text is not None and text.lstrip("-").isdigit() else None


def _rows(name, data, with_payload):
    for kind, at, length, headers, block in salvage(data):
        if kind != "record":
            yield name, at, length, kind, *[None] * 9
            continue
        head, blank, payload = block.partition(b"\r\n\r\n")
        is_http = headers.get("content-type", "").startswith("application/http") and bool(blank)
        payload = payload if is_http else block
        stated = headers.get("warc-payload-digest", "").partition(":")[2] or None
        revisit = headers.get("warc-type") == "revisit"
        if revisit:
            sizes = [line.partition(b":")[2] for line in head.split(b"\r\n") if line.lower().startswith(b"content-length:")]
            size, digest, holds = _number(sizes[0].strip().decode("latin-1")) if sizes else None, stated, None
        else:
            size, digest = len(payload), hashlib.sha256(payload).hexdigest()
            holds = None if stated is None else stated == digest
        yield (
            name, at, length, kind, headers.get("warc-type"), headers.get("warc-record-id"), headers.get("warc-target-uri"), _number(headers.get("x-page-id")),
            _number(headers.get("x-refers-to-page-id")), size, digest, holds, payload if with_payload and not revisit else None,
        )


def round_trip(pages: DataFrame) -> DataFrame:
    """Write ``pages`` to archives in the shared folder and read them back: records and, if any, gaps."""
    path = new_folder(pages.sparkSession, "warc")
    write_warc(pages, path)
    return read_warc(pages.sparkSession, path, with_payload=False)
