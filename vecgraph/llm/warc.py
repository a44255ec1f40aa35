"""WARC archives: segmented writing, revisit records, and reassembly of segments on reading.

Writing: each page is an HTTP response whose body is sent in chunked transfer framing. A block longer than `segment` bytes is cut
into a response record (segment 1) and continuation records that name it as their origin; the last segment states the total length.
Of pages with equal payloads of at least `least` bytes the one with the largest id is stored, the others become revisit records that refer to it.
Files are gzip, with at most `per_file` records each, so their size is bounded however long a page is.

Reading: records of all files are parsed alone; continuation records are grouped by origin identifier, ordered by segment
number and joined; the total length is verified, the chunked framing decoded, and the payload's SHA-1 compared with the header. `intact`
is false where a segment is missing, a length differs, framing is broken or the digest differs; digest and length are then of what could be decoded.

A null html counts as empty, a null url as an empty one. A page with a null id is never the one others refer to, unless no page of its payload has an
id: then all of them are stored. Rows repeated whole are stored as the largest id is, each for itself. An empty table gives an empty archive and result."""

from __future__ import annotations

import gzip
import hashlib
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import prepare, scratch_dir, table

SEGMENT, CHUNK, PER_FILE, LEAST = 16 << 10, 4 << 10, 2048, 1000
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
PARSED = "origin string, segment int, total long, type string, page_id long, url string, refers_to long, declared string, bytes long, digest string, intact boolean, block binary"


def chunked(payload: bytes, size: int = CHUNK) -> bytes:
    parts = [b"%x\r\n%b\r\n" % (len(payload[i : i + size]), payload[i : i + size]) for i in range(0, len(payload), size)]
    return b"".join(parts) + b"0\r\n\r\n"


def unchunked(body: bytes) -> tuple[bytes, bool]:
    """The payload of a chunked body, and whether the framing was whole. Extensions of a chunk's size line and trailers are skipped."""
    out, at = [], 0
    while True:
        line = body.find(b"\r\n", at)
        if line < 0:
            return b"".join(out), False
        try:
            size = int(body[at:line].split(b";")[0].strip(), 16)
        except ValueError:
            return b"".join(out), False
        if size == 0:
            return b"".join(out), body.find(b"\r\n", line + 2) >= 0
        data = body[line + 2 : line + 2 + size]
        out.append(data)
        at = line + 2 + size
        if len(data) < size or body[at : at + 2] != b"\r\n":
            return b"".join(out), False
        at += 2


def record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + f"Content-Length: {len(block)}\r\n\r\n"
    return head.encode() + block + b"\r\n\r\n"


def page_records(identifier: str, page_id: int | None, url: str, payload: bytes, refers_to: int | None, segment: int = SEGMENT) -> Iterator[bytes]:
    """The records of one page; refers_to makes it a revisit."""
    clean = " ".join((url or "").split())
    digest = hashlib.sha1(payload).hexdigest()
    own = [("X-Page-ID", str(page_id))] if page_id is not None else []
    common = [("WARC-Date", DATE), ("WARC-Target-URI", clean), *own, ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http;msgtype=response")]
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n"
    if refers_to is not None:
        yield record([("WARC-Type", "revisit"), ("WARC-Record-ID", identifier), *common, ("WARC-Profile", PROFILE), ("X-Refers-To-Page", str(refers_to)), ("X-Payload-Length", str(len(payload)))], head)
        return
    block = head + chunked(payload)
    pieces = [block[i : i + segment] for i in range(0, len(block), segment)]
    if len(pieces) == 1:
        yield record([("WARC-Type", "response"), ("WARC-Record-ID", identifier), *common], block)
        return
    yield record([("WARC-Type", "response"), ("WARC-Record-ID", identifier), *common, ("WARC-Segment-Number", "1")], pieces[0])
    for k, piece in enumerate(pieces[1:], 2):
        last = [("WARC-Segment-Total-Length", str(len(block)))] if k == len(pieces) else []
        yield record([("WARC-Type", "continuation"), ("WARC-Record-ID", f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, identifier + str(k))}>"), ("WARC-Date", DATE), ("WARC-Segment-Origin-ID", identifier), ("WARC-Segment-Number", str(k)), *last], piece)


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """The records of an archive file without compression: header fields by lower-case name, block. Stops at bytes that are no record."""
    at = 0
    while True:
        while data[at : at + 2] == b"\r\n":
            at += 2
        end = data.find(b"\r\n\r\n", at)
        if data[at : at + 5] != b"WARC/" or end < 0:
            return
        lines = data[at:end].decode("utf-8", "replace").split("\r\n")[1:]
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        size = int(fields.get("content-length", "0"))
        yield fields, data[end + 4 : end + 4 + size]
        at = end + 4 + size


def payload_of(block: bytes) -> tuple[bytes, bool]:
    """The payload of a whole HTTP response block, and whether it was whole."""
    end = block.find(b"\r\n\r\n")
    if end < 0:
        return b"", False
    body = block[end + 4 :]
    return unchunked(body) if b"transfer-encoding: chunked" in block[:end].lower() else (body, True)


def write(pages: DataFrame, path: str, page_id: str = "page_id", url: str = "url", html: str = "html", segment: int = SEGMENT, per_file: int = PER_FILE, least: int = LEAST) -> None:
    prepare(pages.sparkSession)
    payload = F.coalesce(F.col(html).cast("string"), F.lit("")).cast("binary")
    rows = pages.select(F.col(page_id).cast("long").alias("id"), F.col(url).cast("string").alias("url"), payload.alias("payload"))
    rows = rows.withColumns({"digest": F.sha1("payload"), "size": F.octet_length("payload")})
    # counting reads no payload back: only digests and ids are shuffled for it
    first = rows.where(F.col("size") >= least).groupBy(F.col("digest").alias("d"), F.col("size").alias("n")).agg(F.max("id").alias("first"), F.count("*").alias("copies")).where("copies > 1")
    joined = rows.join(first.select("d", "n", "first"), (F.col("digest") == F.col("d")) & (F.col("size") == F.col("n")), "left")
    refers = F.when(F.col("first").isNotNull() & ~F.col("id").eqNullSafe(F.col("first")), F.col("first"))

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, serial = TaskContext.get().partitionId(), 0
        for b in batches:
            held, size = [], 0
            for page, link, body, to in zip(*(b[c] for c in ("id", "url", "payload", "refers")), strict=True):
                identifier = f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page}/{part}/{serial}')}>"
                serial += 1
                for x in page_records(identifier, page.as_py(), link.as_py(), body.as_py(), to.as_py(), segment):
                    held.append(x[:-1])  # the writer ends every row with the last byte
                    size += len(x)
                    if size > 8 << 20:
                        yield pa.record_batch({"record": pa.array(held, pa.binary())})
                        held, size = [], 0
            if held:
                yield pa.record_batch({"record": pa.array(held, pa.binary())})

    out = joined.select("id", "url", "payload", refers.alias("refers")).mapInArrow(records, "record binary")
    out.select(F.col("record").cast("string").alias("value")).write.option("compression", "gzip").option("lineSep", "\n").option("maxRecordsPerFile", per_file).text(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, url, payload_bytes, payload_digest, record_type, refers_to, intact) of every response and revisit of the archives below path."""
    prepare(spark)
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content")

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("origin", pa.string()), ("segment", pa.int32()), ("total", pa.int64()), ("type", pa.string()), ("page_id", pa.int64()), ("url", pa.string()), ("refers_to", pa.int64()), ("declared", pa.string()), ("bytes", pa.int64()), ("digest", pa.string()), ("intact", pa.bool_()), ("block", pa.binary())])
        for b in batches:
            for content in b["content"]:
                data, held, size = content.as_py(), [], 0
                for f, block in parse(gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data):
                    kind = f.get("warc-type")
                    if kind not in ("response", "revisit", "continuation"):
                        continue
                    whole = kind == "response" and "warc-segment-number" not in f
                    number = lambda k, f=f: int(f[k]) if k in f else None
                    row = {"origin": f.get("warc-segment-origin-id") or f.get("warc-record-id"), "segment": number("warc-segment-number") or 1, "total": number("warc-segment-total-length"), "type": kind, "page_id": number("x-page-id"), "url": f.get("warc-target-uri"), "refers_to": number("x-refers-to-page"), "declared": f.get("warc-payload-digest", "").removeprefix("sha1:") or None, "intact": True, "bytes": number("x-payload-length"), "digest": f.get("warc-payload-digest", "").removeprefix("sha1:") if kind == "revisit" else None, "block": None}
                    if whole:
                        payload, ok = payload_of(block)
                        digest = hashlib.sha1(payload).hexdigest()
                        row |= {"bytes": len(payload), "digest": digest, "intact": ok and row["declared"] in (None, digest)}
                    elif kind != "revisit":
                        row["block"] = block
                        size += len(block)
                    held.append(row)
                    if size > 8 << 20 or len(held) >= 4096:
                        yield pa.RecordBatch.from_pylist(held, schema)
                        held, size = [], 0
                if held:
                    yield pa.RecordBatch.from_pylist(held, schema)

    @F.arrow_udf("struct<bytes long, digest string, intact boolean>")
    def assembled(blocks: pa.Array, segments: pa.Array, total: pa.Array, declared: pa.Array) -> pa.Array:
        out = []
        for b, s, t, d in zip(blocks, segments, total, declared, strict=True):
            block = b"".join(x.as_py() or b"" for x in b.values) if b.is_valid else b""
            payload, ok = payload_of(block)
            digest = hashlib.sha1(payload).hexdigest()
            numbers = s.as_py() or []
            out.append({"bytes": len(payload), "digest": digest, "intact": ok and numbers == list(range(1, len(numbers) + 1)) and len(block) == t.as_py() and d.as_py() in (None, digest)})
        return pa.array(out, pa.struct([("bytes", pa.int64()), ("digest", pa.string()), ("intact", pa.bool_())]))

    parsed = files.mapInArrow(records, PARSED)
    single = lambda c: F.max(c).alias(c)
    parts = F.sort_array(F.collect_list(F.when(F.col("block").isNotNull(), F.struct("segment", "block"))))
    grouped = parsed.groupBy("origin").agg(single("total"), F.max(F.when(F.col("type") != "continuation", F.col("type"))).alias("type"), *map(single, ("page_id", "url", "refers_to", "declared", "bytes", "digest")), F.min("intact").alias("intact"), parts.alias("parts"))
    grouped = grouped.where("type is not null").withColumn("_whole", F.size("parts") == 0)
    done = grouped.withColumn("_p", assembled(F.col("parts.block"), F.col("parts.segment"), F.col("total"), F.col("declared")))
    pick = lambda c: F.when(F.col("_whole"), F.col(c)).otherwise(F.col(f"_p.{c}"))
    return done.select("page_id", "url", pick("bytes").alias("payload_bytes"), pick("digest").alias("payload_digest"), F.col("type").alias("record_type"), "refers_to", pick("intact").alias("intact"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_dir(spark, "warc")
    write(table(spark, sf_dir, "pages").select("page_id", "url", "html"), path)
    return read(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact")


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
s AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes, sha1(h) AS payload_digest FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY payload_digest) AS first FROM s)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= 1000 AND page_id <> first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= 1000 AND page_id <> first THEN first END AS refers_to, true AS intact FROM m
"""
