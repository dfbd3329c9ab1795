"""WARC archives: writing with revisits and segments, reading with reassembly of segments and chunked framing."""

from __future__ import annotations

import gzip
import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from landmark_kkm.llm.texts import slices
from landmark_kkm.session import new_path, ship

# Fixed values of the format.
VERSION = b"WARC/1.1"
RECORD_END = "\r\n\r\n"
DATE = b"2024-01-01T00:00:00Z"

#: Payloads of fewer bytes are always stored whole.
REVISIT_BYTES = 1000
SEGMENT_BYTES = 64 << 10
CHUNK_BYTES = 16 << 10
#: With SEGMENT_BYTES this bounds a file, which a reader holds whole: 32 MB.
RECORDS_PER_FILE = 512
#: Revisits up to this many are broadcast (16 bytes each); beyond that pages meet them by a shuffle.
BROADCAST_ROWS = 2_000_000


def chunked(payload: bytes, size: int = CHUNK_BYTES) -> bytes:
    """Chunked transfer framing: hex length, CRLF, bytes, CRLF, and a last chunk of length 0."""
    parts = [b"%x\r\n%s\r\n" % (len(p), p) for p in (payload[i : i + size] for i in range(0, len(payload), size))]
    return b"".join([*parts, b"0\r\n\r\n"])


def unchunked(body: bytes) -> bytes:
    """The payload of chunked framing; extensions and trailers are skipped. Broken framing is a ValueError."""
    out, at = [], 0
    while True:
        end = body.find(b"\r\n", at)
        if end < 0:
            raise ValueError("chunk without length")
        size = int(body[at:end].split(b";")[0], 16)
        at = end + 2
        if size == 0:
            return b"".join(out)
        if body[at + size : at + size + 2] != b"\r\n":
            raise ValueError("chunk without end")
        out.append(body[at : at + size])
        at += size + 2


def record(headers: list[tuple[bytes, bytes]], block: bytes) -> bytes:
    """A record without the two line ends that close it."""
    lines = [VERSION, *(k + b": " + v for k, v in headers), b"Content-Length: %d" % len(block)]
    return b"\r\n".join(lines) + b"\r\n\r\n" + block


def segments(record_id: bytes, headers: list[tuple[bytes, bytes]], block: bytes, size: int = SEGMENT_BYTES) -> Iterator[bytes]:
    """One record, or a first segment and continuations that name it, the last with the total length."""
    own = (b"WARC-Record-ID", b"<%s>" % record_id)
    if len(block) <= size:
        yield record([own, *headers], block)
        return
    cuts = list(range(0, len(block), size))
    yield record([own, *headers, (b"WARC-Segment-Number", b"1")], block[:size])
    for number, at in enumerate(cuts[1:], 2):
        more = [
            (b"WARC-Record-ID", b"<%s;%d>" % (record_id, number)),
            (b"WARC-Type", b"continuation"),
            (b"WARC-Date", DATE),
            (b"WARC-Segment-Origin-ID", b"<%s>" % record_id),
            (b"WARC-Segment-Number", b"%d" % number),
        ]
        if number == len(cuts):
            more.append((b"WARC-Segment-Total-Length", b"%d" % len(block)))
        yield record(more, block[at : at + size])


def _line(value: str | None) -> bytes:
    """A header value on one line."""
    return (value or "").replace("\r", "%0D").replace("\n", "%0A").encode()


def _write(batches: Iterator[pa.RecordBatch], segment_bytes: int) -> Iterator[pa.RecordBatch]:
    part, row = TaskContext.get().partitionId(), 0
    for batch in (b for whole in batches for b in slices(whole, "html")):
        out: list[bytes] = []
        size = 0
        for page, url, html, digest, owner in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "digest", "owner"))):
            payload = (html or "").encode()
            key = b"" if page is None else b"%d" % page
            record_id = b"urn:page:%s:%d.%d" % (key, part, row)
            row += 1
            common = [(b"WARC-Date", DATE), (b"WARC-Target-URI", _line(url)), (b"WARC-Page-ID", key), (b"WARC-Payload-Digest", b"sha1:" + digest.encode())]
            head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
            if owner is None:
                kind = [(b"WARC-Type", b"response"), *common, (b"Content-Type", b"application/http;msgtype=response")]
                found = list(segments(record_id, kind, head + b"Transfer-Encoding: chunked\r\n\r\n" + chunked(payload), segment_bytes))
            else:
                kind = [(b"WARC-Type", b"revisit"), *common, (b"WARC-Refers-To", b"<urn:page:%d>" % owner), (b"WARC-Profile", b"http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
                found = list(segments(record_id, kind, head + b"Content-Length: %d\r\n\r\n" % len(payload), segment_bytes))
            out += found
            size += sum(map(len, found))
            if size > 8 << 20:
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["record"])
                out, size = [], 0
        yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], names=["record"])


def with_owner(pages: DataFrame, revisit_bytes: int = REVISIT_BYTES) -> DataFrame:
    """pages (page_id, url, html) with digest and owner: for a payload of revisit_bytes or more that another page holds too, the largest such page_id; null for that page itself and all others."""
    sized = pages.select("page_id", "url", "html", F.sha1(F.coalesce(F.encode("html", "UTF-8"), F.lit(b""))).alias("digest"))
    large = sized.filter(F.octet_length("html") >= revisit_bytes).select("page_id", "digest")
    owners = large.groupBy("digest").agg(F.max("page_id").alias("owner"), F.count("*").alias("n")).filter("n > 1")
    revisits = large.join(owners, "digest").filter("page_id <> owner").select(F.col("page_id").alias("_page"), F.col("digest").alias("_digest"), "owner").distinct()
    few = revisits.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    met = (sized["page_id"] == revisits["_page"]) & (sized["digest"] == revisits["_digest"])
    return sized.join(F.broadcast(revisits) if few else revisits, met, "left").drop("_page", "_digest")


def write_archives(pages: DataFrame, path: str, segment_bytes: int = SEGMENT_BYTES, revisit_bytes: int = REVISIT_BYTES) -> None:
    """Gzip files of WARC records under path, committed by Spark's own writer, so that lost tasks leave nothing half-written."""
    ship(pages.sparkSession)
    rows = with_owner(pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string")), revisit_bytes)
    records = rows.mapInArrow(lambda it: _write(it, segment_bytes), "record binary").select(F.col("record").cast("string").alias("value"))
    records.write.option("lineSep", RECORD_END).option("compression", "gzip").option("maxRecordsPerFile", RECORDS_PER_FILE).text(path)


def records_of(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers with lower-case names, block) of each record of an archive, gzip or plain."""
    if data[:2] == b"\x1f\x8b":
        data = gzip.decompress(data)
    at = 0
    while at < len(data):
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            raise ValueError("record without header end")
        first, *lines = data[at:end].split(b"\r\n")
        if not first.startswith(b"WARC/"):
            raise ValueError("record without version")
        headers = {k.strip().lower().decode(): v.strip().decode("utf-8", "replace") for k, _, v in (x.partition(b":") for x in lines)}
        length = int(headers["content-length"])
        block = data[end + 4 : end + 4 + length]
        if len(block) != length:
            raise ValueError("record cut short")
        yield headers, block
        at = end + 4 + length + 4


_READ = pa.schema([("origin", pa.string()), ("segment", pa.int32()), ("total", pa.int64()), ("page_id", pa.int64()), ("url", pa.string()), ("type", pa.string()), ("digest", pa.string()), ("refers_to", pa.int64()), ("block", pa.binary()), ("status", pa.string()), ("payload_bytes", pa.int64()), ("payload", pa.binary())])
_READ_DDL = "origin string, segment int, total long, page_id long, url string, type string, digest string, refers_to long, block binary, status string, payload_bytes long, payload binary"


def _parse(batches: Iterator[pa.RecordBatch], payloads: bool) -> Iterator[pa.RecordBatch]:
    """Rows of segments carry their blocks to be put together; records that are whole are decoded at once and carry only what is asked for."""
    bare = lambda x: (x or "").strip("<>")
    for batch in batches:
        for content in batch.column("content"):
            rows = []
            size = 0
            for head, block in records_of(content.as_py()):
                kind = head.get("warc-type", "")
                if kind not in ("response", "revisit", "continuation"):
                    continue
                origin = bare(head.get("warc-segment-origin-id") or head.get("warc-record-id"))
                page, to = head.get("warc-page-id"), bare(head.get("warc-refers-to"))
                rows.append({
                    "origin": origin, "segment": int(head.get("warc-segment-number", 0)), "total": int(head["warc-segment-total-length"]) if "warc-segment-total-length" in head else None,
                    "page_id": int(page) if page else None, "url": head.get("warc-target-uri"), "type": kind,
                    "digest": head.get("warc-payload-digest", "").removeprefix("sha1:") or None, "refers_to": int(to.removeprefix("urn:page:")) if to else None, "block": block,
                })
                if not rows[-1]["segment"]:
                    whole = assembled(rows[-1:])
                    rows[-1] |= {"block": None, "digest": whole["payload_digest"], "status": whole["status"], "payload_bytes": whole["payload_bytes"], "payload": whole["payload"] if payloads else None}
                size += len(rows[-1]["block"] or rows[-1]["payload"] or b"")
                if size > 8 << 20:
                    yield pa.RecordBatch.from_pylist(rows, schema=_READ)
                    rows, size = [], 0
            yield pa.RecordBatch.from_pylist(rows, schema=_READ)


def payload_of(block: bytes) -> tuple[bytes | None, int]:
    """The payload of an HTTP message (None if it has only headers) and its length."""
    head, _, body = block.partition(b"\r\n\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:])}
    if headers.get(b"transfer-encoding", b"").lower() == b"chunked":
        body = unchunked(body)
        return body, len(body)
    length = int(headers.get(b"content-length", len(body)))
    return (body, length) if len(body) == length else (None, length)


def assembled(parts: list[dict]) -> dict:
    """A whole record from its segments in order. status tells what is wrong: orphan (no first segment), gap, length, framing or digest."""
    first, last = parts[0], parts[-1]
    out = {"page_id": first["page_id"], "url": first["url"], "record_type": first["type"], "refers_to": first["refers_to"], "segments": len(parts), "status": "ok", "payload_bytes": None, "payload_digest": first["digest"], "payload": None}
    block = b"".join(p["block"] for p in parts)
    if first["type"] == "continuation":
        return out | {"status": "orphan"}
    if first["segment"] and ([p["segment"] for p in parts] != list(range(1, len(parts) + 1)) or last["total"] is None):
        return out | {"status": "gap"}
    if first["segment"] and last["total"] != len(block):
        return out | {"status": "length"}
    try:
        payload, out["payload_bytes"] = payload_of(block)
    except ValueError:
        return out | {"status": "framing"}
    if payload is not None:
        out["payload"], out["payload_digest"] = payload, hashlib.sha1(payload).hexdigest()
        if first["digest"] and first["type"] == "response" and out["payload_digest"] != first["digest"]:
            out["status"] = "digest"
    return out


_OUT = [("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("segments", pa.int32()), ("status", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("payload", pa.binary())]
_OUT_DDL = "page_id long, url string, record_type string, refers_to long, segments int, status string, payload_bytes long, payload_digest string, payload binary"


def _assemble(batches: Iterator[pa.RecordBatch], payloads: bool) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by (origin, segment); only one record's segments are held at a time."""
    schema = pa.schema(_OUT)
    held: list[dict] = []
    done: list[dict] = []
    size = 0

    def close() -> None:
        nonlocal size
        first = held[0]
        if first["status"]:
            row = {"page_id": first["page_id"], "url": first["url"], "record_type": first["type"], "refers_to": first["refers_to"], "segments": 1, "status": first["status"], "payload_bytes": first["payload_bytes"], "payload_digest": first["digest"], "payload": first["payload"]}
        else:
            row = assembled(held)
        size += len(row["payload"] or b"") if payloads else 0
        done.append(row if payloads else row | {"payload": None})

    for batch in batches:
        for row in batch.to_pylist():
            if held and row["origin"] != held[0]["origin"]:
                close()
                held = []
            held.append(row)
        if len(done) >= 10_000 or size > 8 << 20:
            yield pa.RecordBatch.from_pylist(done, schema=schema)
            done, size = [], 0
    if held:
        close()
    yield pa.RecordBatch.from_pylist(done, schema=schema)


def read_archives(spark: SparkSession, path: str, payloads: bool = True) -> DataFrame:
    """One row per response or revisit under path: page_id, url, record_type, refers_to, segments, status, payload_bytes, payload_digest and (payloads) payload.

    Continuations are grouped by their origin and ordered by segment number; the total length, the framing and the digest are verified, and what
    fails keeps its row with a status other than ok. Files may be gzip or plain. A revisit has its payload's length and digest, not its bytes."""
    ship(spark)
    files = spark.read.format("binaryFile").load(path).select("content")
    parsed = files.mapInArrow(lambda it: _parse(it, payloads), _READ_DDL)
    count = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return parsed.repartition(count, "origin").sortWithinPartitions("origin", "segment").mapInArrow(lambda it: _assemble(it, payloads), _OUT_DDL)


def round_trip(spark: SparkSession, pages: DataFrame) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to, segments, status) of every page, written to archives in the shared folder and read back.

    Null html is an empty payload. Payloads under 1000 bytes are always responses. A null page_id stays null, is a response and is never referred to.
    Repeated rows each have a record. An empty table gives no rows."""
    path = new_path(spark, "warc")
    write_archives(pages, path)
    found = read_archives(spark, path, payloads=False)
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "segments", "status")


#: What the archives must give back, in SQL.
WARC_SQL = """
WITH p AS (
  SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest FROM pages
), o AS (
  SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS owner FROM p
)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 1000 AND owner <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND owner <> page_id THEN owner END AS refers_to
FROM o
"""
