import base64
import hashlib
import random

import pytest

from bedvoids.llm import warc as W

SCHEMA = "page_id long, url string, html string, name string, payload int"


def made():
    r = random.Random(4)
    rows = [(0, "http://a.example/x y", None, "n", 1), (1, None, "", "n", 1), (2, "http://b.example", "WARC/1.1\r\n\r\nContent-Length: 5\r\n\r\n", "n", 1)]
    for i in range(3, 60):
        rows.append((i, f"http://h{i}.example/é", "".join(r.choice("aé日\r\n<>0\x00") for _ in range(r.choice([0, 5, 400, 3000]))), "n", 1))
    rows += [(60, "http://copy.example", rows[20][2], "n", 1), (61, "http://copy2.example", rows[20][2], "n", 1), (62, "u", "long " * 60000, "n", 1)]
    return rows


def want(rows):
    last = {}
    for p, _, h, *_ in rows:
        last[h or ""] = max(p, last.get(h or "", -1))
    sha = lambda h: base64.b32encode(hashlib.sha1((h or "").encode()).digest()).decode()
    return sorted((p, len((h or "").encode()), sha(h), "response" if p == last[h or ""] else "revisit", None if p == last[h or ""] else last[h or ""]) for p, _, h, *_ in rows)


@pytest.mark.parametrize("segment,archive", [(1 << 20, 16 << 20), (700, 5000), (97, 1 << 20)])
def test_round_trip(spark, segment, archive):
    rows = made()
    if segment < 100:
        rows = rows[:40]
    out = W.round_trip(spark.createDataFrame(rows, SCHEMA).repartition(3), segment, archive)
    got = sorted((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in out.collect())
    assert got == want(rows)


def test_payloads_come_back(spark, tmp_path):
    rows = made()
    W.write(spark.createDataFrame(rows, SCHEMA), str(tmp_path / "w"), segment=500, least=1 << 40)
    back = {int(r.id.split(":")[2]): bytes(r.payload) for r in W.read(spark, str(tmp_path / "w")).collect()}
    assert back == {p: (h or "").encode() for p, _, h, *_ in rows}


def test_ordinary_pages_are_cut_and_reassembled(spark, tmp_path):
    """With the query's own parameters most records of the given pages go through their segments."""
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    W.write(pages, str(tmp_path / "w"))
    segments = spark.read.format("binaryFile").load(str(tmp_path / "w")).select("content").mapInArrow(W._segments, W._SEGMENTS)
    assert segments.where("type = 'continuation'").count() > pages.count()


def test_rows_of_one_page_id_are_apart(spark):
    big, other = "long text " * 600, "another " * 500
    rows = [(7, "u", big, "n", 1), (7, "u", other, "n", 1), (7, "v", big, "n", 1), (7, "v", big, "n", 1), (3, "w", other, "n", 1), (None, "x", big, "n", 1), (None, None, None, "n", 1), (None, None, None, "n", 1), (9, "y", None, "n", 1)]
    out = W.round_trip(spark.createDataFrame(rows, SCHEMA).repartition(3), segment=700)
    got = sorted(((r.page_id, r.payload_bytes, r.record_type, r.refers_to, r.url) for r in out.collect()), key=str)
    want = [(7, 6000, "response", None, "u"), (7, 4000, "response", None, "u"), (7, 6000, "response", None, "v"), (7, 6000, "response", None, "v"), (3, 4000, "revisit", 7, "w"), (None, 6000, "response", None, "x"), (None, 0, "response", None, ""), (None, 0, "response", None, ""), (9, 0, "response", None, "y")]
    assert got == sorted(want, key=str)


def test_framing():
    body = b"x" * 40000
    assert W.unchunked(W.chunked(body)) == body and W.unchunked(W.chunked(b"")) == b""
    assert W.unchunked(b"3;ext=1\r\nabc\r\n0\r\nTrailer: 1\r\n\r\n") == b"abc"
    with pytest.raises(ValueError, match="length"):
        W.unchunked(b"2\r\nabc\r\n0\r\n\r\n")


def test_lost_segments_are_seen():
    import pyarrow as pa

    part = lambda n, total, block, origin="o": {"origin": origin, "number": n, "total": total, "type": "response", "uri": "u", "digest": None, "refers": None, "block": block}
    whole = W._HEAD.encode() + W.chunked(b"hello")
    first, second = part(1, None, whole[:9]), part(2, len(whole), whole[9:])
    read = lambda *rows: [x for b in W._reassemble(pa.RecordBatch.from_pylist([r]) for r in rows) for x in b.column("payload").to_pylist()]
    assert read(first, second) == [b"hello"]
    assert read(first, first, second, second, part(1, len(whole), whole, "p")) == [b"hello"] * 3
    with pytest.raises(ValueError, match="segments"):
        read(first, part(3, len(whole), whole[9:]))
    with pytest.raises(ValueError, match="times"):
        read(first, first, second)


def test_empty(spark):
    assert W.round_trip(spark.createDataFrame([], SCHEMA)).count() == 0
