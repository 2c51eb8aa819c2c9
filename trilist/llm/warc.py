"""WARC archives with segmented records and chunked transfer framing.

Writing: one record per page, an HTTP response whose body is chunked. A record longer than ``segment`` bytes is split into a
first segment and continuation records that name it as their origin and carry their segment number; the last one carries
the total length. Spark's text writer stores the records (they end in the writer's line separator, two CRLFs), so
archives are committed like any Spark output, gzipped, on any file system Spark can write to. As no record is longer than a segment
and its header, an archive of ``PER_FILE`` records is bounded in bytes too (about 7 MB), whatever the pages' lengths.

Reading: archives are parsed by Content-Length; continuation records are grouped by origin, ordered by segment number and
checked against the total length, then chunks are decoded and the payload's digest is checked against its header.

Revisits: of records with equal payloads of ``least`` bytes or more, the one with the smallest page_id holds the payload
and the others revisit it.

Edge cases: null html is an empty payload; a null page_id is written without an id header, never is the smallest (unless all
are null) and comes back as null; rows that repeat the smallest page_id are all responses; a null url is an empty target;
characters are never cut by a chunk or segment; an empty table writes no record; other columns are ignored. A missing or
surplus segment, a wrong length or a wrong digest raises ValueError.
"""

from __future__ import annotations

import gzip
import hashlib
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, join_hot, materialise, read_table, scratch, text_of

SEGMENT, CHUNK, LEAST, PER_FILE = 8_192, 1_024, 100, 800
DATE = "2024-01-01T00:00:00Z"
END = b"\r\n\r\n"


def pieces(data: bytes, size: int) -> list[bytes]:
    """Pieces of at most size bytes that end between characters."""
    out, at = [], 0
    while at < len(data):
        end = min(at + size, len(data))
        while end < len(data) and data[end] & 0xC0 == 0x80:
            end -= 1
        out.append(data[at:end])
        at = end
    return out


def chunked(payload: bytes, size: int) -> bytes:
    return b"".join(b"%x\r\n%b\r\n" % (len(p), p) for p in pieces(payload, size)) + b"0\r\n\r\n"


def unchunked(body: bytes) -> bytes:
    """Decode chunked framing, with chunk extensions and trailers."""
    out, at = [], 0
    while True:
        line = body.index(b"\r\n", at)
        size = int(body[at:line].split(b";")[0], 16)
        if not size:
            return b"".join(out)
        if body[line + 2 + size : line + 4 + size] != b"\r\n":
            raise ValueError("a chunk does not end where it says")
        out.append(body[line + 2 : line + 2 + size])
        at = line + 4 + size


def header(fields: list[tuple[str, str]]) -> bytes:
    return b"WARC/1.1\r\n" + "\r\n".join(f"{k}: {v}" for k, v in fields).encode() + END


def records(name: str, page_id: str | None, url: str, payload: bytes, digest: str, refers_to: str | None, segment: int, chunk: int) -> list[bytes]:
    """The records of one page, without the two CRLFs after each."""
    own = hashlib.md5(name.encode()).hexdigest()
    uuid = lambda h: f"<urn:uuid:{h[:8]}-{h[8:12]}-{h[12:16]}-{h[16:20]}-{h[20:]}>"
    fields = [("WARC-Record-ID", uuid(own)), ("WARC-Date", DATE), ("WARC-Target-URI", quote(url, safe="%/:?#[]@!$&'()*+,;=~")), ("WARC-Payload-Digest", f"sha256:{digest}")]
    fields += [("X-Page-Id", page_id)] if page_id is not None else []
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked" + END
    if refers_to is not None:
        more = [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("X-Refers-To-Page", refers_to), ("Content-Type", "application/http;msgtype=response"), ("Content-Length", str(len(http)))]
        return [header([("WARC-Type", "revisit"), *fields, *more]) + http]
    block = http + chunked(payload, chunk)
    parts = pieces(block, segment)
    out = []
    for k, part in enumerate(parts, 1):
        head = [("WARC-Type", "response" if k == 1 else "continuation")]
        if k == 1:
            head += fields
        else:
            head += [("WARC-Record-ID", uuid(hashlib.md5(f"{own}:{k}".encode()).hexdigest())), ("WARC-Date", DATE), ("WARC-Segment-Origin-ID", uuid(own))]
        if len(parts) > 1:
            head.append(("WARC-Segment-Number", str(k)))
        if k == len(parts) > 1:
            head.append(("WARC-Segment-Total-Length", str(len(block))))
        out.append(header([*head, ("Content-Type", "application/http;msgtype=response"), ("Content-Length", str(len(part)))]) + part)
    return out


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (lower-case names) and block of each record of an uncompressed archive."""
    at = 0
    while at < len(data):
        end = data.index(END, at)
        lines = data[at:end].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"not a record: {lines[0][:40]!r}")
        fields = {k.lower(): v for k, v in (x.split(": ", 1) for x in lines[1:])}
        size = int(fields["content-length"])
        block = data[end + 4 : end + 4 + size]
        if data[end + 4 + size : end + 8 + size] != END or len(block) != size:
            raise ValueError("a record does not end where it says")
        yield fields, block
        at = end + 8 + size


def write_archives(pages: DataFrame, path: str, least: int = LEAST, segment: int = SEGMENT, chunk: int = CHUNK) -> None:
    """Write pages (page_id, url, html) as gzipped archives under path."""
    html = text_of("html")
    rows = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), html.alias("html"), F.sha2(html, 256).alias("digest"), (F.octet_length(html) >= least).alias("large"))
    light = materialise(rows.filter("large").select("page_id", "digest"), "warc-digests")
    first = light.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).filter("n > 1")
    known = join_hot(rows.filter("large"), materialise(first, "warc-first"), ["digest"], "n", light.count(), how="left")
    planned = known.select("page_id", "url", "html", "digest", "first").unionByName(rows.filter("NOT large").select("page_id", "url", "html", "digest", F.lit(None).cast(pages.schema["page_id"].dataType).alias("first")))
    again = F.when(F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.col("first").cast("string"))
    ready = planned.select(F.concat_ws(":", F.lit("row"), F.monotonically_increasing_id().cast("string"), F.col("page_id").cast("string")).alias("name"), F.col("page_id").cast("string").alias("page_id"), "url", F.col("html").cast("binary").alias("html"), "digest", again.alias("refers_to"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [r.decode() for row in zip(*(c.to_pylist() for c in b.columns)) for r in records(*row, segment, chunk)]
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.string())], names=["value"])

    text = ready.mapInArrow(run, "value string")
    text.write.option("lineSep", "\r\n\r\n").option("compression", "gzip").option("maxRecordsPerFile", PER_FILE).text(path)


def payload_of(block: bytes, fields: dict) -> tuple[bytes, str]:
    http, _, body = block.partition(END)
    payload = unchunked(body) if b"transfer-encoding: chunked" in http.lower() else body
    digest = hashlib.sha256(payload).hexdigest()
    if fields.get("digest") not in (None, digest):
        raise ValueError("a payload's digest is not the one in its header")
    return payload, digest


def read_archives(spark, path: str) -> DataFrame:
    """Rows (page_id string, url, record_type, digest, refers_to string, payload binary); revisits have no payload."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                raw = content.as_py()
                out = []
                for f, block in parse(gzip.decompress(raw) if raw[:2] == b"\x1f\x8b" else raw):
                    digest = f.get("warc-payload-digest", "").removeprefix("sha256:") or None
                    number, payload = int(f.get("warc-segment-number", 0)), None
                    if number:
                        payload = block
                    elif f["warc-type"] == "response":
                        payload, digest = payload_of(block, {"digest": digest})
                    origin = f.get("warc-segment-origin-id", f["warc-record-id"])
                    total = f.get("warc-segment-total-length")
                    out.append((f["warc-type"], f.get("x-page-id"), f.get("warc-target-uri"), digest, f.get("x-refers-to-page"), origin, number, int(total) if total else None, payload))
                cols = list(zip(*out)) or [[]] * 9
                kinds = [pa.string()] * 6 + [pa.int32(), pa.int64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["record_type", "page_id", "url", "digest", "refers_to", "origin", "number", "total", "payload"])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for segments in b.column(0).to_pylist():
                segments.sort(key=lambda s: s["number"])
                block = b"".join(s["payload"] for s in segments)
                if [s["number"] for s in segments] != list(range(1, len(segments) + 1)) or segments[-1]["total"] != len(block):
                    raise ValueError(f"segments of {segments[0]['origin']} are not whole")
                first = segments[0]
                payload, digest = payload_of(block, first)
                out.append((first["page_id"], first["url"], first["record_type"], digest, None, payload))
            cols = list(zip(*out)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.string()] * 5 + [pa.binary()])], names=["page_id", "url", "record_type", "digest", "refers_to", "payload"])

    archives = spark.read.format("binaryFile").load(path).select("content")
    schema = "record_type string, page_id string, url string, digest string, refers_to string, origin string, number int, total long, payload binary"
    found = archives.mapInArrow(scan, schema)
    whole = found.filter("number = 0").select("page_id", "url", "record_type", "digest", "refers_to", "payload")
    parts = found.filter("number > 0").groupBy("origin").agg(F.collect_list(F.struct("number", "total", "page_id", "url", "record_type", "digest", "origin", "payload")).alias("segments"))
    return whole.unionByName(parts.select("segments").mapInArrow(join, "page_id string, url string, record_type string, digest string, refers_to string, payload binary"))


def op10_segment_reassembly(spark, sf_dir: str) -> DataFrame:
    """All pages into archives and back; a revisit's size comes from the response it refers to."""
    pages = read_table(spark, sf_dir, "pages")
    bounded_batches(spark)
    path = scratch(spark, "warc")
    write_archives(pages, path)
    read = read_archives(spark, path).select("page_id", "record_type", "digest", "refers_to", F.octet_length("payload").cast("long").alias("size"))
    read = materialise(read, "warc-read")
    again = read.filter("record_type = 'revisit'").drop("size")
    sizes = read.filter("record_type = 'response'").groupBy("digest").agg(F.max("size").alias("size"))
    wanted = again.groupBy("digest").agg(F.count("*").alias("n"))
    total = wanted.agg(F.sum("n")).first()[0] or 0
    revisits = join_hot(again, sizes.join(wanted, "digest"), ["digest"], "n", total)
    both = read.filter("record_type = 'response'").unionByName(revisits.select("page_id", "record_type", "digest", "refers_to", "size"))
    kind = pages.schema["page_id"].dataType
    return both.select(F.col("page_id").cast(kind).alias("page_id"), F.col("size").alias("payload_bytes"), F.col("digest").alias("payload_digest"), "record_type", F.col("refers_to").cast(kind).alias("refers_to"))


OP10_SQL = """
WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, '')))::BIGINT AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
q AS (SELECT *, CASE WHEN payload_bytes >= 100 THEN min(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS first FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id IS NOT DISTINCT FROM first THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id IS DISTINCT FROM first THEN first END AS refers_to FROM q
"""
