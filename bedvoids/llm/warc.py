"""Web archives: writing pages as WARC records, and reassembling records from their segments.

A page is an HTTP response whose body is sent in chunks. Blocks longer than `segment` bytes are cut into
a first record and continuation records, which name the first one as their origin. Reading groups them by
origin, orders them by segment number, checks numbers and total length, and takes the chunk framing off.
Of pages with equal payloads one is stored, the others are revisit records that refer to it.

Archives are files of about `archive` bytes in a folder that all executors share; each is written whole by
one task and read whole, so memory is bounded by its size. Segments are dealt by origin and sorted there; a
task holds the segments of one record at a time.

Null html counts as an empty payload. Record ids hold page_id, payload digest and a digest of the URL, so rows with
the same page_id, or without one, are records of their own. Rows that agree in all three are one record, written and
read back as often as the row stands. Of several rows with the largest page_id of a payload each is a response, and
so are rows without page_id. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import fresh_path, store

#: Segments are short enough that ordinary pages are cut into several.
SEGMENT, ARCHIVE, CHUNK = 1 << 10, 16 << 20, 1 << 9
#: Revisits of one page are dealt to so many tasks.
SALT = 32
_HEAD = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n"
_REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_SEGMENTS = "origin string, number int, total long, type string, uri string, digest string, refers string, block binary"
_RECORDS = "id string, type string, uri string, digest string, refers string, payload binary, payload_bytes long, payload_digest string"


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def chunked(body: bytes, size: int = CHUNK) -> bytes:
    out = []
    for i in range(0, len(body), size):
        part = body[i : i + size]
        out += [b"%x\r\n" % len(part), part, b"\r\n"]
    return b"".join([*out, b"0\r\n\r\n"])


def unchunked(data: bytes) -> bytes:
    """Takes chunk framing off; trailers are left out, chunk extensions ignored."""
    out, at = [], 0
    while True:
        end = data.index(b"\r\n", at)
        size = int(data[at:end].split(b";")[0], 16)
        at = end + 2
        if size == 0:
            return b"".join(out)
        if data[at + size : at + size + 2] != b"\r\n":
            raise ValueError("a chunk doesn't end where its length says")
        out.append(data[at : at + size])
        at += size + 2


def payload_of(block: bytes) -> bytes:
    """Body of an HTTP response, without transfer coding."""
    head, gap, body = block.partition(b"\r\n\r\n")
    if not gap:
        raise ValueError("an HTTP head without end")
    return unchunked(body) if re.search(rb"(?im)^transfer-encoding:[^\r\n]*\bchunked\b", head) else body


def record(fields: list[tuple[str, str]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", str(len(block)))])
    return b"WARC/1.1\r\n" + head.encode() + b"\r\n" + block + b"\r\n\r\n"


def records_of(name: str, uri: str, kind: str, sha: str, refers: str | None, payload: bytes, segment: int) -> Iterator[bytes]:
    """The WARC records of a page: one, or a first one and its continuations."""
    base = [("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Target-URI", uri), ("WARC-Payload-Digest", f"sha1:{sha}")]
    if kind == "revisit":
        yield record([("WARC-Type", "revisit"), ("WARC-Record-ID", f"<{name}>"), *base, ("WARC-Profile", _REVISIT), ("WARC-Refers-To", f"<{refers}>"), ("Content-Type", "application/http;msgtype=response")], _HEAD.encode())
        return
    block = _HEAD.encode() + chunked(payload)
    parts = [block[i : i + segment] for i in range(0, len(block), segment)]
    typed = ("Content-Type", "application/http;msgtype=response")
    if len(parts) == 1:
        yield record([("WARC-Type", "response"), ("WARC-Record-ID", f"<{name}>"), *base, typed], block)
        return
    for i, part in enumerate(parts, 1):
        own = [("WARC-Type", "response"), ("WARC-Record-ID", f"<{name}>"), *base, typed] if i == 1 else [("WARC-Type", "continuation"), ("WARC-Record-ID", f"<{name}:{i}>"), base[0], ("WARC-Target-URI", uri), ("WARC-Segment-Origin-ID", f"<{name}>")]
        last = [("WARC-Segment-Total-Length", str(len(block)))] if i == len(parts) else []
        yield record([*own, ("WARC-Segment-Number", str(i)), *last], part)


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (lower-case names) and block of each record, by the lengths the records give."""
    at = 0
    while True:
        while data[at : at + 2] == b"\r\n":
            at += 2
        if at >= len(data):
            return
        end = data.index(b"\r\n\r\n", at)
        first, *lines = data[at:end].decode().split("\r\n")
        if not first.startswith("WARC/1."):
            raise ValueError(f"no WARC record at byte {at}")
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        begin, size = end + 4, int(fields["content-length"])
        if begin + size > len(data):
            raise ValueError(f"a record is cut off at byte {at}")
        yield fields, data[begin : begin + size]
        at = begin + size


def _pack(segment: int, archive: int):
    """Archives as text rows; the writer's line end completes the last record."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[bytes] = []
        size = 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([b"".join(held)[:-2]], pa.binary())], names=["archive"])

        for batch in batches:
            for i in range(batch.num_rows):
                name, uri, kind, refers, payload, sha = (batch.column(c)[i].as_py() for c in ("name", "url", "kind", "refers", "payload", "sha"))
                sha = base64.b32encode(bytes.fromhex(sha)).decode()
                for part in records_of(name, re.sub(r"[\x00-\x20]", "%20", uri or ""), kind, sha, refers, payload, segment):
                    if held and size + len(part) > archive:
                        yield out()
                        held, size = [], 0
                    held.append(part)
                    size += len(part)
        if held:
            yield out()

    return run


def _segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    strip = lambda v: None if v is None else v.strip("<>")
    schema = pa.schema([("origin", pa.string()), ("number", pa.int32()), ("total", pa.int64()), ("type", pa.string()), ("uri", pa.string()), ("digest", pa.string()), ("refers", pa.string()), ("block", pa.binary())])

    def out(rows: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    for batch in batches:
        for content in batch.column("content"):
            data, rows, size = content.as_py(), [], 0
            if data[:2] == b"\x1f\x8b":
                parts = []
                while data:  # a member for each record or for all
                    d = zlib.decompressobj(31)
                    parts.append(d.decompress(data))
                    data = d.unused_data
                data = b"".join(parts)
            for f, block in parse(data):
                segmented = "warc-segment-number" in f
                total = int(f["warc-segment-total-length"]) if "warc-segment-total-length" in f else None if segmented else len(block)
                rows.append((strip(f.get("warc-segment-origin-id", f["warc-record-id"])), int(f.get("warc-segment-number", 0)), total, f["warc-type"], f.get("warc-target-uri"), f.get("warc-payload-digest"), strip(f.get("warc-refers-to")), block))
                size += len(block)
                if size > 4 << 20:
                    yield out(rows)
                    rows, size = [], 0
            if rows:
                yield out(rows)


def _finish(rows: list[tuple]) -> pa.RecordBatch:
    """Records with payload from (origin, type, uri, digest, refers, block)."""
    cols: list[list] = [[] for _ in range(8)]
    for name, kind, uri, sha, refers, block in rows:
        payload = payload_of(block) if kind == "response" else None
        got = digest(payload) if payload is not None else None
        if got is not None and sha and sha.removeprefix("sha1:") != got:
            raise ValueError(f"the payload of {name} doesn't have the digest of its record")
        for c, v in zip(cols, (name, kind, uri, (sha or "").removeprefix("sha1:") or None, refers, payload, None if payload is None else len(payload), got), strict=True):
            c.append(v)
    kinds = [pa.string()] * 5 + [pa.binary(), pa.int64(), pa.string()]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["id", "type", "uri", "digest", "refers", "payload", "payload_bytes", "payload_digest"])


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        yield _finish(list(zip(*(batch.column(c).to_pylist() for c in ("origin", "type", "uri", "digest", "refers", "block")), strict=True)))


def _joined(origin: str, rows: list[tuple]) -> tuple:
    """A record from its segments (number, total, type, uri, digest, refers, block), in order of their numbers."""
    block, total = b"".join(r[6] for r in rows), rows[-1][1]
    if [r[0] for r in rows] != list(range(1, len(rows) + 1)) or total != len(block):
        raise ValueError(f"segments {[r[0] for r in rows]} of {origin} have {len(block)} of {total} bytes")
    _, _, kind, uri, sha, refers, _ = rows[0]
    return origin, kind, uri, sha, refers, block


def _reassemble(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Segments sorted by origin and number come in; each origin's stand together, if in several batches."""
    last, rows, copies = None, [], []
    done, size = [], 0

    def out() -> Iterator[pa.RecordBatch]:
        nonlocal done, size
        if rows:
            if len(set(copies)) > 1:
                raise ValueError(f"segments of {last} stand {copies} times")
            for _ in range(copies[0]):  # a row that stood several times in the table
                done.append(_joined(last, rows))
                size += len(done[-1][5])
                if size > 4 << 20 or len(done) > 1 << 14:
                    yield _finish(done)
                    done, size = [], 0

    for batch in batches:
        for origin, *row in zip(*(batch.column(c).to_pylist() for c in ("origin", "number", "total", "type", "uri", "digest", "refers", "block")), strict=True):
            if origin != last:
                yield from out()
                last, rows, copies = origin, [], []
            if rows and rows[-1][0] == row[0]:
                copies[-1] += 1
            else:
                rows.append(row)
                copies.append(1)
    yield from out()
    if done:
        yield _finish(done)


def write(pages: DataFrame, path: str, segment: int = SEGMENT, archive: int = ARCHIVE, least: int = 0) -> None:
    """Archives of (page_id, url, html). Payloads of at least `least` bytes that are equal are stored once, with the largest page_id."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.encode(F.coalesce("html", F.lit("")), "utf-8").alias("payload"))
    rows = rows.withColumn("sha", F.sha1("payload")).withColumn("size", F.octet_length("payload")).withColumn("own", F.coalesce(F.md5(F.encode("url", "utf-8")), F.lit("")))
    # digests of several rows are kept apart first: few of them go to every task, many are joined in parts
    few = F.struct("page_id", "own")
    first = rows.where(F.col("size") >= least).groupBy("sha", "size").agg(F.max(few).alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1 and first.page_id is not null").drop("m")
    roles = rows.join(store(first, "digests"), ["sha", "size"], "left")
    again = F.col("first").isNotNull() & (F.col("page_id") != F.col("first.page_id"))
    name = lambda page, own: F.concat_ws(":", F.lit("urn:page"), F.coalesce(page.cast("string"), F.lit("")), "sha", own)
    own = name(F.col("page_id"), F.col("own"))
    out = roles.select(own.alias("name"), "url", F.when(F.coalesce(again, F.lit(False)), "revisit").otherwise("response").alias("kind"), F.when(again, name(F.col("first.page_id"), F.col("first.own"))).alias("refers"), F.when(again, F.lit(None)).otherwise(F.col("payload")).alias("payload"), "sha")
    out = out.withColumn("payload", F.coalesce("payload", F.unhex(F.lit(""))))
    packed = out.mapInArrow(_pack(segment, archive), "archive binary")
    packed.select(F.col("archive").cast("string").alias("value")).write.option("lineSep", "\r\n").option("maxRecordsPerFile", 1).option("compression", "gzip").text(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """Records of all archives below `path`: segments reassembled, payloads decoded and checked against their digests."""
    files = spark.read.format("binaryFile").load(path).select("content")
    segments = files.mapInArrow(_segments, _SEGMENTS)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # records in one piece are origins with one segment
    whole = F.when(F.col("number") == 0, 1).otherwise(F.col("number")).cast("int").alias("number")
    parts = segments.select("origin", whole, *[c for c in segments.columns if c not in ("origin", "number")])
    return parts.repartition(n, "origin").sortWithinPartitions("origin", "number").mapInArrow(_reassemble, _RECORDS)


def round_trip(pages: DataFrame, segment: int = SEGMENT, archive: int = ARCHIVE) -> DataFrame:
    """Writes `pages`, reads the archives back: page_id, payload_bytes, payload_digest, record_type, refers_to, url."""
    spark = pages.sparkSession
    path = fresh_path(spark, "warc")
    write(pages, path, segment, archive)
    number = lambda c: F.split(F.col(c), ":")[2].try_cast("long")
    # what is used several times below is read from the archives once, without the payloads
    records = store(read(spark, path).select("id", "type", "uri", "digest", "refers", "payload_bytes", "payload_digest"), "records")
    # revisits meet one row for each page that is referred to, in several tasks
    sizes = records.where("type = 'response'").join(records.where("refers is not null").select(F.col("refers").alias("id")).distinct(), "id").select(F.col("id").alias("first"), F.col("payload_bytes").alias("bytes"), F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))).alias("salt"))
    back = records.where("type = 'revisit'").withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALT)).cast("int")).join(sizes.withColumnRenamed("salt", "s"), (F.col("refers") == F.col("first")) & (F.col("salt") == F.col("s")))
    columns = lambda size, sha, refers: [number("id").alias("page_id"), size.alias("payload_bytes"), sha.alias("payload_digest"), F.col("type").alias("record_type"), refers.alias("refers_to"), F.col("uri").alias("url")]
    own = records.where("type = 'response'").select(*columns(F.col("payload_bytes"), F.col("payload_digest"), F.lit(None).cast("long")))
    return own.unionByName(back.select(*columns(F.col("bytes"), F.col("digest"), number("refers"))))


#: Base32 is made from a digest's hexadecimal form, five bits at a time.
SQL = """
WITH sized AS (
  SELECT page_id, coalesce(url, '') AS url, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS payload_bytes, sha1(coalesce(html, '')) AS hex FROM pages
), named AS (
  SELECT *, array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST((CAST('0x' || substr(hex, 10 * (i // 8) + 1, 10) AS BIGINT) >> (35 - 5 * (i % 8))) & 31 AS BIGINT) + 1, 1)), '') AS payload_digest,
    max(page_id) OVER (PARTITION BY hex, payload_bytes) AS newest
  FROM sized
)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = newest THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = newest THEN NULL ELSE newest END AS refers_to, url
FROM named
"""
