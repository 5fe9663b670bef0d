"""WARC archives: writing with revisits and segments, reading with reassembly.

A page becomes one record: ``response`` with its payload, or ``revisit`` if an
equal payload of at least ``MIN_REVISIT`` bytes stands under a smaller page_id.
Blocks longer than ``segment_bytes`` are cut: the first segment is the response,
the others are ``continuation`` records that name it as their origin; the last
one tells the total length. Segmented responses use chunked transfer framing.
Each record is a gzip member of its own, so a record is found by its offset.

Reading parses each archive once. Whole records end there; of segments only the
places in the files are kept, grouped by origin, ordered by segment number and
read again where they are put together. Payloads are never shuffled.

Defined cases: null html is an empty payload; a null url gives no target header
and line breaks in it are escaped; pages of one page_id with equal payloads are
all ``response`` if that page_id is the smallest; a long payload is held by one
task at a time, in segments on disk; an empty table gives no rows; other columns,
whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .store import executor_fs, materialise, scratch_path, write_atomically

MIN_REVISIT = 100
SEGMENT_BYTES = 16 << 10
#: Rows of one payload go to so many partitions.
SALTS = 64
_CHUNK = 4096
_DATE = "2024-01-01T00:00:00Z"


def chunked(body: bytes, size: int = _CHUNK) -> bytes:
    parts = []
    for at in range(0, len(body), size):
        piece = body[at : at + size]
        parts += [b"%x\r\n" % len(piece), piece, b"\r\n"]
    return b"".join(parts) + b"0\r\n\r\n"


def unchunked(body: bytes) -> bytes:
    """The payload of a chunked body; raises ValueError on broken framing."""
    out, at = [], 0
    while True:
        line = body.find(b"\r\n", at)
        if line < 0:
            raise ValueError("chunk size missing")
        size, at = int(body[at:line].split(b";")[0], 16), line + 2
        if size == 0:
            return b"".join(out)
        if body[at + size : at + size + 2] != b"\r\n":
            raise ValueError("chunk shorter than its size")
        out.append(body[at : at + size])
        at += size + 2


def record(headers: list[tuple[str, object]], block: bytes, level: int = 4) -> bytes:
    """One record as a gzip member; headers without a value are left out."""
    lines = ["WARC/1.1"] + [f"{k}: {v}" for k, v in headers if v is not None] + [f"Content-Length: {len(block)}", "", ""]
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(lines).encode()) + packer.compress(block) + packer.compress(b"\r\n\r\n") + packer.flush()


def page_records(page_id, url, payload: bytes, digest: str, refers_to, record_id: str, segment_bytes: int) -> Iterator[bytes]:
    """The records of one page."""
    target = url.replace("\r", "%0D").replace("\n", "%0A") if url is not None else None
    about = [("WARC-Date", _DATE), ("WARC-Target-URI", target), ("X-Page-ID", page_id)]
    http = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
    if refers_to is not None:
        head = [("WARC-Type", "revisit"), ("WARC-Record-ID", f"<{record_id}>"), *about, ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Refers-To-Page-ID", refers_to), ("Content-Type", "application/http; msgtype=response")]
        yield record(head, f"{http}Content-Length: {len(payload)}\r\n\r\n".encode())
        return
    if len(payload) > segment_bytes:
        block = f"{http}Transfer-Encoding: chunked\r\n\r\n".encode() + chunked(payload)
    else:
        block = f"{http}Content-Length: {len(payload)}\r\n\r\n".encode() + payload
    head = [("WARC-Type", "response"), ("WARC-Record-ID", f"<{record_id}>"), *about, ("WARC-Payload-Digest", f"sha256:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    if len(payload) <= segment_bytes:
        yield record(head, block)
        return
    pieces = [block[at : at + segment_bytes] for at in range(0, len(block), segment_bytes)]
    yield record([*head, ("WARC-Segment-Number", 1)], pieces[0])
    for number, piece in enumerate(pieces[1:], 2):
        total = len(block) if number == len(pieces) else None
        yield record([("WARC-Type", "continuation"), ("WARC-Record-ID", f"<{record_id}:{number}>"), ("WARC-Date", _DATE), ("WARC-Segment-Origin-ID", f"<{record_id}>"), ("WARC-Segment-Number", number), ("WARC-Segment-Total-Length", total)], piece)


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """(headers, block) of one inflated record."""
    head, found, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in lines[1:])}
    size = int(headers.get("content-length", -1))
    if not found or not lines[0].startswith("WARC/1.") or size < 0 or rest[size:] != b"\r\n\r\n":
        raise ValueError("broken record")
    return headers, rest[:size]


def read_records(uri: str) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(offset, compressed size, headers, block) of each record of an archive, one in memory at a time."""
    fs, path = executor_fs(uri)
    with fs.open_input_stream(path, compression=None) as stream:
        at, buffer = 0, b""
        while True:
            buffer = buffer or stream.read(1 << 20)
            if not buffer:
                return
            inflate, out, size = zlib.decompressobj(31), [], 0
            while True:
                out.append(inflate.decompress(buffer))
                if inflate.eof:
                    size += len(buffer) - len(inflate.unused_data)
                    buffer = inflate.unused_data
                    break
                size += len(buffer)
                buffer = stream.read(1 << 20)
                if not buffer:
                    raise ValueError(f"{path} ends inside a record")
            yield at, size, *parse(b"".join(out))
            at += size


def http_payload(block: bytes) -> tuple[bytes, dict[str, str]]:
    """(payload, headers) of an HTTP response, transfer framing decoded."""
    head, _, body = block.partition(b"\r\n\r\n")
    headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode().split("\r\n")[1:])}
    return (unchunked(body) if headers.get("transfer-encoding") == "chunked" else body), headers


def first_pages(pages: DataFrame, min_bytes: int = MIN_REVISIT) -> DataFrame:
    """(digest, first_page) of payloads that more than one page has; sums before the shuffle."""
    return pages.groupBy("digest").agg(F.min("page_id").alias("first_page"), F.count("*").alias("n"), F.first("bytes").alias("bytes")).where((F.col("n") > 1) & (F.col("bytes") >= min_bytes)).select("digest", "first_page")


def write_archives(pages: DataFrame, path: str, min_bytes: int = MIN_REVISIT, segment_bytes: int = SEGMENT_BYTES) -> DataFrame:
    """Write all of ``pages`` (page_id, url, html) below ``path``; one row (path, n_records) per archive."""
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    sized = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html", F.sha2(payload, 256).alias("digest"), F.octet_length(F.coalesce("html", F.lit(""))).alias("bytes"))
    repeated = first_pages(sized.select("page_id", "digest", "bytes"), min_bytes)
    spread = repeated.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salted = sized.withColumn("salt", F.pmod(F.hash("page_id"), F.lit(SALTS)))
    ready = salted.join(spread, ["digest", "salt"], "left").select("page_id", "url", "html", "digest", F.when(F.col("first_page") != F.col("page_id"), F.col("first_page")).alias("refers_to"))

    def write(batches):
        from pyspark import TaskContext

        shard, count = TaskContext.get().partitionId(), [0]

        def chunks():
            for batch in batches:
                for row in zip(*(c.to_pylist() for c in batch.columns)):
                    page_id, url, html, digest, refers_to = row
                    yield from page_records(page_id, url, (html or "").encode(), digest, refers_to, f"urn:page:{shard}:{count[0]}", segment_bytes)
                    count[0] += 1

        uri = f"{path}/part-of-crawl-{shard:08d}.warc.gz"
        write_atomically(uri, chunks())
        yield pa.RecordBatch.from_pydict({"path": [uri], "n_records": pa.array(count, pa.int64())})

    return ready.mapInArrow(write, "path string, n_records long")


_FOUND = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, origin string, segment int, total long, path string, offset long, size long"
_RESULT = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]


def _whole(headers: dict[str, str], block: bytes) -> tuple:
    """The result columns of a whole record; its digest is verified."""
    payload, http = http_payload(block)
    told = headers.get("warc-payload-digest", "").removeprefix("sha256:")
    page = int(headers["x-page-id"]) if "x-page-id" in headers else None
    if headers["warc-type"] == "revisit":
        return page, int(http["content-length"]), told, "revisit", int(headers["x-refers-to-page-id"])
    digest = hashlib.sha256(payload).hexdigest()
    if digest != told:
        raise ValueError(f"payload of {headers.get('warc-record-id')} has another digest than told")
    return page, len(payload), digest, "response", None


def read_archives(archives: DataFrame) -> DataFrame:
    """Per page of the archives (path): page_id, payload_bytes, payload_digest, record_type, refers_to.

    Only the archives' paths come to the driver. A missing segment, a wrong
    total length or a wrong digest raises.
    """
    spark = archives.sparkSession
    paths = [r.path for r in archives.select("path").collect()]
    if not paths:
        return spark.createDataFrame([], _FOUND).select(*_RESULT)

    def scan(batches):
        for batch in batches:
            for uri in batch.column("path").to_pylist():
                rows = []
                for offset, size, headers, block in read_records(uri):
                    if "warc-segment-number" in headers:
                        origin = headers.get("warc-segment-origin-id") or headers["warc-record-id"]
                        total = headers.get("warc-segment-total-length")
                        rows.append((*[None] * 5, origin, int(headers["warc-segment-number"]), int(total) if total else None, uri, offset, size))
                    else:
                        rows.append((*_whole(headers, block), *[None] * 6))
                    if len(rows) == 20_000:
                        yield as_batch(rows)
                        rows = []
                yield as_batch(rows)

    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string()}
    fields = [x.split() for x in _FOUND.split(", ")]

    def as_batch(rows):
        columns = list(zip(*rows)) or [()] * len(fields)
        return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(columns, fields)], [n for n, _ in fields])

    def assemble(batches):
        for batch in batches:
            rows = []
            for origin, segments in zip(batch.column("origin").to_pylist(), batch.column("segments").to_pylist()):
                if [s["segment"] for s in segments] != list(range(1, len(segments) + 1)):
                    raise ValueError(f"segments of {origin} are missing or repeated")
                blocks, first = [], None
                for s in segments:
                    fs, path = executor_fs(s["path"])
                    with fs.open_input_file(path) as file:
                        headers, block = parse(zlib.decompress(file.read_at(s["size"], s["offset"]), 31))
                    first = first or headers
                    blocks.append(block)
                block = b"".join(blocks)
                if len(block) != segments[-1]["total"]:
                    raise ValueError(f"{origin} has {len(block)} bytes, not {segments[-1]['total']}")
                rows.append((*_whole(first, block), *[None] * 6))
            yield as_batch(rows)

    listed = spark.createDataFrame([(p,) for p in paths], "path string").repartition(len(paths))
    found = materialise(listed.mapInArrow(scan, _FOUND), "warc-records")
    # an origin's segments are few: a record's length by the segment length
    grouped = found.where("origin is not null").groupBy("origin").agg(F.array_sort(F.collect_list(F.struct("segment", "total", "path", "offset", "size"))).alias("segments"))
    return found.where("origin is null").select(*_RESULT).unionByName(grouped.mapInArrow(assemble, _FOUND).select(*_RESULT))


def round_trip(pages: DataFrame, path: str | None = None, **options) -> DataFrame:
    """Write ``pages`` as archives and read them back; see the two steps."""
    path = path or scratch_path(pages.sparkSession, "archives")
    return read_archives(write_archives(pages, path, **options))


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
d AS (SELECT page_id, octet_length(encode(body)) AS n, sha256(body) AS digest FROM p),
f AS (SELECT *, min(page_id) OVER (PARTITION BY digest) AS first_page FROM d)
SELECT page_id, n::BIGINT AS payload_bytes, digest AS payload_digest,
       CASE WHEN n >= 100 AND first_page <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 100 AND first_page <> page_id THEN first_page END AS refers_to FROM f
"""
