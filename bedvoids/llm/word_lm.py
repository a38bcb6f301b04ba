"""Cross-entropy difference of documents under a target and a background model of words.

Both models share the vocabulary of the corpus: every string between white space that stands in it, as it is
written. n-grams of up to ORDER words are counted over all texts, none dropped, and the table of counts is dealt
over the cluster by the n-gram's 56-bit hash, so it grows with the corpus and nothing of it goes to the driver.
Documents lie in buckets, compressed; each bucket asks once for each n-gram in it, with its own counts, and gets back
what the rest of the corpus counts in the same order, so the joins move each n-gram once a bucket, however common it is,
and answers for what stands nowhere else are zeros.

A word's share in the target is mixed with its share in the background (MIX), each longer context adds its
counts to STRENGTH times what the shorter one says. The end of a text counts as a word. A document's score is
its mean loss over words and end under the target less that under the background, in bits: the lower, the more
like the target. Texts without words, or null, have a null score. Without target documents both models are the
background's and scores are 0. Repeated rows are counted as often as they stand; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H

ORDER, MIX, STRENGTH = 3, 0.1, 2.0

#: n-grams are known by 56 bits of a hash: two of 10 ** 13 different ones share theirs with a probability of 1 in 7,000 each.
_KNOWN = ~H.U(255)
_ROOT, _START, _END = H.mix(np.arange(1, 4).astype(H.U)) & _KNOWN
_STEP = H.U(0x100000001B3)


def _planes(x: np.ndarray) -> bytes:
    """Numbers byte by byte, all first bytes, then all second ones, so that they compress; how many stands before them."""
    raw = np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8).T)
    return len(x).to_bytes(8, "little") + pa.Codec("zstd", 1).compress(raw, asbytes=True)


def _numbers(x: pa.Scalar, kind: type = np.int64) -> np.ndarray:
    x = x.as_buffer()
    n = int.from_bytes(x.slice(0, 8).to_pybytes(), "little")
    raw = np.frombuffer(pa.Codec("zstd").decompress(x.slice(8), 8 * n), np.uint8)
    return np.ascontiguousarray(raw.reshape(8, -1).T).view(kind).ravel()


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of a batch as one compressed row for each bucket."""
    codec = pa.Codec("zstd", 3)
    for batch in batches:
        bucket = batch.column("bucket").to_numpy()
        order = np.argsort(bucket, kind="stable")
        cut = np.flatnonzero(np.r_[True, np.diff(bucket[order]) > 0]) if len(order) else []
        out = []
        for at in np.split(order, cut[1:]) if len(order) else []:
            rows = batch.select(["doc_id", "text"]).take(pa.array(at))
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rows.schema) as writer:
                writer.write_batch(rows)
            raw = sink.getvalue()
            out.append((int(bucket[at[0]]), raw.size.to_bytes(8, "little") + codec.compress(raw, asbytes=True)))
        cols = list(zip(*out, strict=True)) or [[], []]
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.binary())], names=["bucket", "rows"])


def _unpacked(packed: pa.Table) -> pa.Table:
    """doc_id and text of a bucket's rows, in an order that only the rows set."""
    codec, parts = pa.Codec("zstd"), []
    for x in sorted(packed["rows"].to_pylist()):
        raw = codec.decompress(x[8:], int.from_bytes(x[:8], "little"))
        parts.append(pa.ipc.open_stream(raw).read_all())
    return pa.concat_tables(parts)


def sequences(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words with a start before and an end after each text that has any: hash, row and place in it; words of each row."""
    data, bounds = H.text_buffer(column)
    word = [np.zeros(0, H.U)]
    count = np.zeros(len(bounds) - 1, np.int64)
    for i, j in H.pieces(bounds):
        part, cut = data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i]
        lo, hi, at = H.words(part, cut)
        word.append(H.span(H.prefix(part), lo, hi))
        count[i:j] = np.bincount(at, minlength=j - i)
    size = np.where(count > 0, count + 2, 0)
    rows = np.repeat(np.arange(len(count), dtype=np.int32), size)
    place = np.arange(len(rows), dtype=np.int32) - np.repeat((np.cumsum(size) - size).astype(np.int32), size)
    seq = np.full(len(rows), _END, H.U)
    seq[place == 0] = _START
    seq[(place > 0) & (place <= count[rows])] = np.concatenate(word)
    return seq, rows, place, count


def orders(seq: np.ndarray, place: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each n: the hash of the n-gram that ends at each place, and where there is one."""
    g = H.mix(seq + _ROOT) & _KNOWN
    yield g, np.ones(len(seq), bool)
    for n in range(2, ORDER + 1):
        g = np.r_[np.zeros(min(1, len(seq)), H.U), H.mix(g[:-1] * _STEP + seq[1:]) & _KNOWN]
        yield g, place >= n - 1


def _merged(got: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """The n-grams of all orders, sorted, with their counts, and the root."""
    g, n = (np.concatenate(x) for x in zip(*got, (np.array([_ROOT]), np.ones(1, np.int64)), strict=True))
    order = np.argsort(g, kind="stable")
    g, n = g[order], n[order]
    first = np.flatnonzero(np.r_[True, g[1:] != g[:-1]])  # hashes of two orders may meet
    return g[first], np.add.reduceat(n, first)


def _part(g: np.ndarray, parts: int) -> np.ndarray:
    """The part that an n-gram is dealt to; rises with the hash."""
    return ((g >> H.U(32)) * H.U(parts)) >> H.U(32)


def _ask(parts: int):
    schema = pa.schema([("part", pa.int32()), ("bucket", pa.int32()), ("g", pa.binary()), ("t", pa.binary()), ("b", pa.binary())])

    def run(packed: pa.Table, ids: pa.Table) -> pa.Table:
        if not packed.num_rows:
            return schema.empty_table()
        bucket, texts = packed["bucket"][0].as_py(), _unpacked(packed)
        mine = np.isin(texts["doc_id"].fill_null(0).to_numpy(), ids["doc_id"].to_numpy()) & texts["doc_id"].is_valid().to_numpy()
        seq, rows, place, _ = sequences(texts["text"])
        del texts
        mine, all_, own = mine[rows], [], []
        for x, there in orders(seq, place):
            all_.append(np.unique(x[there], return_counts=True))
            own.append(np.unique(x[there & mine], return_counts=True))
        (g, b), (g_t, n_t) = _merged(all_), _merged(own)
        t = np.zeros(len(g), np.int64)
        t[np.searchsorted(g, g_t)] = n_t
        root = np.searchsorted(g, _ROOT)
        b[root], t[root] = (place > 0).sum(), ((place > 0) & mine).sum()
        part = _part(g, parts)
        cut = np.searchsorted(part, np.arange(parts + 1).astype(H.U))
        out = []
        for k in np.flatnonzero(np.diff(cut)):
            s = slice(cut[k], cut[k + 1])
            out.append((int(k), bucket, _planes(np.diff(g[s], prepend=H.U(0))), _planes(t[s]), _planes(b[s])))
        return pa.table([pa.array(x, kind) for x, kind in zip(zip(*out, strict=True), schema.types, strict=True)], schema=schema)

    return run


def _sum(asked: pa.Table) -> pa.Table:
    """What the other buckets count together, to each in the order in which it asked."""
    got = [np.cumsum(_numbers(x, H.U), dtype=H.U) for x in asked["g"]]
    g = np.unique(np.concatenate(got))
    t, b = np.zeros(len(g), np.int64), np.zeros(len(g), np.int64)
    where = [np.searchsorted(g, x) for x in got]
    for at, x, y in zip(where, asked["t"], asked["b"], strict=True):
        t[at] += _numbers(x)
        b[at] += _numbers(y)
    # the target's counts in full: a bucket that scores doesn't know which of its texts are the target's
    more = [(_planes(t[at]), _planes(b[at] - _numbers(y))) for at, y in zip(where, asked["b"], strict=True)]
    return pa.table({"bucket": asked["bucket"], "part": asked["part"], "t": pa.array([x for x, _ in more], pa.binary()), "b": pa.array([y for _, y in more], pa.binary())})


def _score(packed: pa.Table, replies: pa.Table) -> pa.Table:
    texts = _unpacked(packed)
    ids, (seq, rows, place, count) = texts["doc_id"], sequences(texts["text"])
    del texts
    bits = np.zeros((2, len(count)))
    if len(rows):
        got, at, ends = [], [], []
        for x, there in orders(seq, place):
            ends.append(np.flatnonzero(there).astype(np.int32))
            g, where, n = np.unique(x[there], return_inverse=True, return_counts=True)
            got.append((g, n))
            at.append(where.astype(np.int32))
        del seq, x, there, where
        g, b = _merged(got)
        root = np.searchsorted(g, _ROOT)
        b[root] = (place > 0).sum()
        replies = replies.sort_by("part")
        t, more = (np.concatenate([_numbers(x) for x in replies[k]]) for k in ("t", "b"))
        assert len(t) == len(g), "a bucket asks for the same n-grams each time"
        b += more
        del more, replies
        if not t[root]:
            t = b
        own = [np.searchsorted(g, x).astype(np.int32) for x, _ in got]
        del g, got
        event = place > 0
        for k, n in enumerate((t, b)):
            share = (b[own[0]] / b[root])[at[0]]
            p = (1 - MIX) * (n[own[0]] / n[root])[at[0]] + MIX * share if k == 0 else share
            seen = n[own[0]].astype(float)[at[0]]
            for to, where, end in zip(own[1:], at[1:], ends[1:], strict=True):
                here = n[to].astype(float)[where]
                p[end] = (here + STRENGTH * p[end]) / (seen[end - 1] + STRENGTH)
                seen[end] = here
            bits[k] = np.bincount(rows[event], -np.log2(p[event]), len(count))
    with np.errstate(invalid="ignore", divide="ignore"):
        x, y = bits / (count + 1)
    empty = count == 0
    return pa.table({"doc_id": ids, "n_tokens": pa.array(count, pa.int64()), **{k: pa.array(v, pa.float64(), mask=empty) for k, v in (("target_bits", x), ("background_bits", y), ("score", x - y))}})


def scores(docs: DataFrame, target: DataFrame) -> DataFrame:
    """doc_id, n_tokens, target_bits, background_bits, score for each row; `target` holds the doc_ids of the target."""
    n = max(1, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    bucket = F.pmod(F.xxhash64(F.col("doc_id")), F.lit(2 * n)).cast("int").alias("bucket")
    # texts without id aren't the target's, so any bucket will do
    spread = F.pmod(F.when(F.col("doc_id").isNull(), F.xxhash64("text")).otherwise(F.xxhash64("doc_id")), F.lit(2 * n)).cast("int").alias("bucket")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).select(spread, "doc_id", "text")
    ids = target.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct().select(bucket, "doc_id")
    by_bucket = texts.mapInArrow(_pack, "bucket int, rows binary").groupBy("bucket")
    asked = by_bucket.cogroup(ids.groupBy("bucket")).applyInArrow(_ask(2 * n), "part int, bucket int, g binary, t binary, b binary")
    replies = asked.groupBy("part").applyInArrow(_sum, "bucket int, part int, t binary, b binary")
    return by_bucket.cogroup(replies.groupBy("bucket")).applyInArrow(_score, "doc_id long, n_tokens long, target_bits double, background_bits double, score double")
