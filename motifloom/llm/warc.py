"""WARC archives: segmented writing with revisits, and reassembly on reading.

Writing: of pages with equal payloads of at least min_revisit bytes the one with the largest id is a
response and the others revisit it. A response block is an HTTP message in chunked transfer framing;
a block longer than segment_bytes is cut into a first record and continuation records. Records are
committed by Spark's text writer with the WARC record separator, gzip-compressed, a bounded number
of bounded records per file, on any file system that Spark can write.

Reading: each file is parsed by declared lengths. Records of one segment are decoded where they are
read; continuation records are dealt by origin identifier, ordered by segment number, checked for
gaps and for the declared total length, and only then is the chunked framing decoded.

Defined results: null html is an empty payload; a null id is written as none and never chosen as
the response of others unless all ids are null; rows repeating an id are records of their own; a
record that cannot be reassembled has status `incomplete` and a null payload; an empty table gives
no archive and an empty result; further columns are ignored, whatever their names; a payload of any
length is cut into segments.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifloom.llm.common import scratch, ship, text_bytes

SEGMENT_BYTES = 16 << 10
CHUNK_BYTES = 4 << 10
RECORDS_PER_FILE = 1500
MIN_REVISIT = 0
SEPARATOR = "\r\n\r\n"


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _cut(data: bytes, size: int) -> Iterator[bytes]:
    """Pieces of about size bytes that never part a UTF-8 character."""
    at = 0
    while at < len(data):
        end = min(at + size, len(data))
        while end < len(data) and end > at + 1 and data[end] & 0xC0 == 0x80:
            end -= 1
        yield data[at:end]
        at = end


def encode_chunks(payload: bytes, size: int = CHUNK_BYTES) -> bytes:
    return b"".join(b"%x\r\n%b\r\n" % (len(p), p) for p in _cut(payload, size)) + b"0\r\n\r\n"


def decode_chunks(framed: bytes) -> bytes:
    """The payload of chunked framing; ValueError if a frame is broken."""
    out, at = [], 0
    while True:
        line = framed.index(b"\r\n", at)
        size = int(framed[at:line].split(b";")[0], 16)
        at = line + 2
        if size == 0:
            return b"".join(out)
        if framed[at + size : at + size + 2] != b"\r\n":
            raise ValueError("a chunk does not end where it should")
        out.append(framed[at : at + size])
        at += size + 2


def _record(headers: list[tuple[str, object]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", len(block))])
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block


def page_records(page: object, url: str, payload: bytes, digest: str, winner: object, is_revisit: bool, unique: str, segment_bytes: int = SEGMENT_BYTES) -> Iterator[bytes]:
    """All records of one page. unique tells rows apart that repeat an id."""
    origin = f"<urn:x-page:{page}#{unique}>"
    url = "".join(c for c in url if c > " ") or "about:blank"
    common = [("WARC-Type", "revisit" if is_revisit else "response"), ("WARC-Record-ID", origin), ("WARC-Target-URI", url), ("WARC-Date", "1970-01-01T00:00:00Z"), ("WARC-Payload-Digest", f"sha1:{digest}"), ("X-Payload-Length", len(payload)), ("Content-Type", "application/http; msgtype=response")]
    if is_revisit:
        profile = ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")
        yield _record([*common, profile, ("WARC-Refers-To", f"<urn:x-page:{winner}>")], b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n")
        return
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n" + encode_chunks(payload)
    pieces = list(_cut(block, segment_bytes))
    if len(pieces) == 1:
        yield _record(common, block)
        return
    for k, piece in enumerate(pieces, 1):
        last = [("WARC-Segment-Total-Length", len(block))] if k == len(pieces) else []
        if k == 1:
            yield _record([*common, ("WARC-Segment-Number", 1)], piece)
        else:
            yield _record([("WARC-Type", "continuation"), ("WARC-Record-ID", f"<urn:x-page:{page}#{unique}.{k}>"), ("WARC-Date", "1970-01-01T00:00:00Z"), ("WARC-Segment-Origin-ID", origin), ("WARC-Segment-Number", k), *last], piece)


def parse_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers (names in lower case) and block of every record of an uncompressed archive."""
    at = 0
    while at < len(data):
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8", "replace").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("no WARC record where one should start")
        headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(headers["content-length"])
        block = data[end + 4 : end + 4 + size]
        if len(block) < size:
            raise ValueError("a record is cut short")
        yield headers, block
        at = end + 4 + size + 4


def _digests(batches):
    for batch in batches:
        bodies = [x.as_py() for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(b) for b in bodies], pa.int64()), pa.array([payload_digest(b) for b in bodies], pa.string())], names=["page_id", "payload_bytes", "digest"])


def _writer(segment_bytes: int):
    def run(batches):
        from pyspark import TaskContext

        part, row = TaskContext.get().partitionId(), 0
        held, weight = [], 0
        for batch in batches:
            columns = [c.to_pylist() if i != 2 else c for i, c in enumerate(batch.columns)]
            for page, url, body, digest, winner, revisit in zip(*columns):
                for record in page_records(page, url, body.as_py(), digest, winner, revisit, f"{part}-{row}", segment_bytes):
                    held.append(record)
                    weight += len(record)
                row += 1
                if weight > 4 << 20:
                    yield pa.RecordBatch.from_arrays([pa.array(held, pa.binary())], names=["record"])
                    held, weight = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(held, pa.binary())], names=["record"])

    return run


def _with_digest(batches):
    for batch in batches:
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([payload_digest(x.as_py()) for x in batch.column(2)], pa.string())], names=["page_id", "url", "body", "digest"])


def write_archives(pages: DataFrame, path: str, min_revisit: int = MIN_REVISIT, segment_bytes: int = SEGMENT_BYTES, records_per_file: int = RECORDS_PER_FILE) -> None:
    """Writes every row of pages (page_id, url, html) to archives in the folder path."""
    ship(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce(F.col("url").cast("string"), F.lit("")).alias("url"), text_bytes("html").alias("body"))
    sums = rows.select("page_id", "body").mapInArrow(_digests, "page_id long, payload_bytes long, digest string")
    winners = sums.groupBy("digest", "payload_bytes").agg(F.max("page_id").alias("winner")).select("digest", "winner", "payload_bytes")
    full = rows.mapInArrow(_with_digest, "page_id long, url string, body binary, digest string")
    chosen = full.join(winners, "digest")
    revisit = (F.col("payload_bytes") >= min_revisit) & ~F.col("page_id").eqNullSafe(F.col("winner"))
    records = chosen.select("page_id", "url", "body", "digest", "winner", revisit.alias("revisit")).mapInArrow(_writer(segment_bytes), "record binary")
    records.select(F.col("record").cast("string").alias("value")).write.option("lineSep", SEPARATOR).option("compression", "gzip").option("maxRecordsPerFile", records_per_file).text(path)


_PART = [("origin", pa.string()), ("segment_no", pa.int32()), ("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("status", pa.string()), ("total", pa.int64()), ("block", pa.binary()), ("payload", pa.binary())]
_PART_SQL = "origin string, segment_no int, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, status string, total long, block binary, payload binary"


def _page_of(urn: str) -> int | None:
    number = urn.removeprefix("<urn:x-page:").rstrip(">").partition("#")[0]
    return None if number == "None" else int(number)


def _resolve(headers: dict[str, str], block: bytes, payloads: bool) -> dict:
    """What one whole response or revisit says."""
    declared = headers["warc-payload-digest"].removeprefix("sha1:")
    out = {"origin": headers["warc-record-id"], "page_id": _page_of(headers["warc-record-id"]), "record_type": headers["warc-type"]}
    if headers["warc-type"] == "revisit":
        return out | {"payload_bytes": int(headers["x-payload-length"]), "payload_digest": declared, "refers_to": _page_of(headers["warc-refers-to"]), "status": "ok"}
    head, _, body = block.partition(b"\r\n\r\n")
    try:
        payload = decode_chunks(body) if b"transfer-encoding: chunked" in head.lower() else body
    except ValueError:
        return out | {"status": "incomplete"}
    digest = payload_digest(payload)
    return out | {"payload_bytes": len(payload), "payload_digest": digest, "status": "ok" if digest == declared else "digest differs", "payload": payload if payloads else None}


def _batch(rows: list[dict]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r.get(n) for r in rows], t) for n, t in _PART], names=[n for n, _ in _PART])


def _reader(payloads: bool):
    def run(batches):
        for batch in batches:
            for content in batch.column(0):
                held, weight = [], 0
                for headers, block in parse_records(zlib.decompress(content.as_py(), 47)):
                    if "warc-segment-number" in headers:
                        first = headers["warc-type"] != "continuation"
                        row = {"origin": headers["warc-record-id"] if first else headers["warc-segment-origin-id"], "segment_no": int(headers["warc-segment-number"]), "block": block, "total": int(headers["warc-segment-total-length"]) if "warc-segment-total-length" in headers else None}
                        if first:
                            row |= {"record_type": headers["warc-type"], "payload_digest": headers["warc-payload-digest"]}
                    else:
                        row = _resolve(headers, block, payloads)
                    held.append(row)
                    weight += 200 + len(row.get("block") or b"") + len(row.get("payload") or b"")
                    if weight > 4 << 20:
                        yield _batch(held)
                        held, weight = [], 0
                if held:
                    yield _batch(held)

    return run


def _assembler(payloads: bool):
    def run(batches):
        names = [n for n, _ in _PART]
        parts: list[dict] = []

        def whole() -> dict:
            first, last = parts[0], parts[-1]
            block = b"".join(p["block"] for p in parts)
            if [p["segment_no"] for p in parts] != list(range(1, len(parts) + 1)) or last["total"] != len(block):
                return {"origin": first["origin"], "page_id": _page_of(first["origin"]), "record_type": first["record_type"], "status": "incomplete"}
            return _resolve({"warc-record-id": first["origin"], "warc-type": first["record_type"], "warc-payload-digest": first["payload_digest"]}, block, payloads)

        for batch in batches:
            held = []
            for values in zip(*[c.to_pylist() for c in batch.columns]):
                row = dict(zip(names, values))
                if parts and parts[0]["origin"] != row["origin"]:
                    held.append(whole())
                    parts = []
                if row["segment_no"] is None:
                    held.append(row)
                else:
                    parts.append(row)
            if held:
                yield _batch(held)
        if parts:
            yield _batch([whole()])

    return run


def read_archives(spark: SparkSession, path: str, payloads: bool = True) -> DataFrame:
    """One row per page record: page_id, payload_bytes, payload_digest, record_type, refers_to, status, payload."""
    ship(spark)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(path).select("content")
    parts = files.mapInArrow(_reader(payloads), _PART_SQL).repartition("origin").sortWithinPartitions("origin", "segment_no")
    return parts.mapInArrow(_assembler(payloads), _PART_SQL).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "status", "payload")


def round_trip(pages: DataFrame, min_revisit: int = MIN_REVISIT, path: str | None = None, **options) -> DataFrame:
    """Writes pages to archives in the shared folder and reads them back."""
    spark = pages.sparkSession
    path = path or scratch(spark, "warc")
    write_archives(pages, path, min_revisit, **options)
    return read_archives(spark, path, payloads=False).drop("payload")
