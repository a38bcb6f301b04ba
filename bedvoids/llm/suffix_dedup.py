"""Removal of byte strings that stand more than once anywhere in a collection.

Every string of `window` bytes is covered by one block: its least hash of `gram` bytes, and all starts
in a row with that same least hash. Equal strings have the same least hash, so copies can only be found
among blocks of one key. A block that stands more than once is a copy as a whole, which a keyed cryptographic
digest of its bytes verifies; where blocks of a key differ (a passage begins or ends in them), the suffixes in the
different ones are sorted too: prefix hashes and binary search give the common extension of two suffixes in a
logarithmic number of steps, a mergesort orders them, and neighbours that agree on `window` bytes are compared byte
by byte. Groups of suffixes are sorted some at a time, so a task holds a few numbers for each byte of its largest key.
Where too many blocks of a key, or bytes in them, differ for one task, their windows are grouped over the cluster by the
prefix hash of a part that neighbouring ones have in common, and verified by the same digest; what is found is the same.

Null and empty texts, and texts shorter than `window`, have no repeats. Repeated rows count as documents
of their own. Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H
from .store import store

WINDOW, GRAM = 200, 64
#: Keys with more differing blocks, or bytes in them, than this are resolved over the cluster instead of by a sort in one task.
WIDE_KEY, WIDE_BYTES = 2000, 1 << 21
#: Suffixes that are sorted, or merged on a level, at once.
AT_ONCE = 1 << 16
#: Over the cluster, so many neighbouring windows at most go together.
TOGETHER = 32

_BLOCKS = "h long, b long, doc_id long, mark long, lo int, n int, again boolean"
_CONTEXTS = "h long, b long, bytes binary"
_RANGES = "h long, b long, s int, e int"


def verifiers(data: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """64 bits of a keyed BLAKE2 digest of each data[lo:hi]: what agrees in them and in a prefix hash is taken as equal bytes."""
    view, digest = memoryview(np.ascontiguousarray(data)), hashlib.blake2b(key=b"whole bytes", digest_size=8)
    out = bytearray()
    for i, j in zip(lo.tolist(), hi.tolist(), strict=True):
        d = digest.copy()
        d.update(view[i:j])
        out += d.digest()
    return np.frombuffer(out, H.U)


def _least(h: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of `width` values."""
    out, have = h, 1
    while have * 2 <= width:
        out, have = np.minimum(out[:-have], out[have:]), have * 2
    rest = width - have
    return np.minimum(out[:-rest], out[rest:]) if rest else out


def blocks_of(data: np.ndarray, bounds: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """row, first start, number of starts, key, digest of the whole block, and whether the key's hash stands in it more than once."""
    width = window - gram + 1
    if len(data) < window:
        return tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, H.U, H.U, bool))
    p = H.prefix(data)
    at = np.arange(len(data) - gram + 1)
    h = H.span(p, at, at + gram)
    m = _least(h, width)
    row = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
    inside = row[: len(m)] == row[window - 1 :]
    new = np.r_[True, (m[1:] != m[:-1]) | (row[1 : len(m)] != row[: len(m) - 1]) | (inside[1:] != inside[:-1])]
    lo = np.flatnonzero(new)
    hi = np.r_[lo[1:], len(m)]
    keep = inside[lo]
    lo, hi = lo[keep], hi[keep]
    key = m[lo]
    runs = np.lib.stride_tricks.sliding_window_view(h, width)
    again = np.zeros(len(lo), bool)
    for i in range(0, len(lo), 8192):
        k = key[i : i + 8192, None]
        left = (runs[lo[i : i + 8192]] == k).argmax(1) + lo[i : i + 8192]
        right = hi[i : i + 8192] - 1 + width - 1 - (runs[hi[i : i + 8192] - 1][:, ::-1] == k).argmax(1)
        again[i : i + 8192] = left != right
    whole = verifiers(data, lo, hi + window - 1)
    return row[lo], lo - bounds[row[lo]], hi - lo, key, whole, again


def _emit_blocks(window: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, bounds = H.text_buffer(batch.column("text"))
            ids, marks = batch.column("doc_id"), batch.column("mark")
            for i, j in H.pieces(bounds):
                row, lo, n, key, whole, again = blocks_of(data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i], window, gram)
                if len(row):
                    at = pa.array(row + i)
                    yield pa.RecordBatch.from_arrays([H.longs(key), H.longs(whole), ids.take(at), marks.take(at), pa.array(lo.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(again)], names=["h", "b", "doc_id", "mark", "lo", "n", "again"])

    return run


def _emit_contexts(window: int):
    """The bytes of the blocks asked for in each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, bounds = H.text_buffer(batch.column("text"))
            asked = batch.column("asked")
            where = np.repeat(np.arange(batch.num_rows), np.diff(asked.offsets.to_numpy()))
            flat = asked.flatten()
            h, b, lo, n = (flat.field(x).to_numpy(zero_copy_only=False) for x in ("h", "b", "lo", "n"))
            begin = bounds[where] + lo
            size = n.astype(np.int64) + window - 1
            ends = np.r_[0, np.cumsum(size)]
            for i, j in H.pieces(ends):
                out = np.r_[0, np.cumsum(size[i:j])]
                take = np.repeat(begin[i:j] - out[:-1], size[i:j]) + np.arange(out[-1])
                yield pa.RecordBatch.from_arrays([H.longs(h[i:j]), H.longs(b[i:j]), H.binary(data[take], out)], names=["h", "b", "bytes"])

    return run


class Suffixes:
    """Suffixes of one buffer, compared on their first `most` bytes."""

    def __init__(self, data: np.ndarray, most: int):
        self.data, self.p, self.most = data, H.prefix(data), most
        self.powers = H.powers(len(self.p))[0]
        self.steps = [1 << s for s in reversed(range(most.bit_length()))]
        # the first eight bytes as a number that orders as they do
        self.head = np.zeros(len(data), H.U)
        for k in range(8):
            self.head[: len(data) - k] |= data[k:].astype(H.U) << H.U(8 * (7 - k))

    def common(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the common extension: binary search over hashes of prefixes."""
        got = np.zeros(len(i), np.int64)
        powers = self.powers
        for step in self.steps:
            to = got + step
            fits = to <= self.most
            to = np.where(fits, to, got)
            same = (self.p[i + to] - self.p[i]) * powers[i] == (self.p[j + to] - self.p[j]) * powers[j]
            got = np.where(fits & same, to, got)
        return got

    def sign(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """-1, 0 or 1: most suffixes differ early or not at all, and only the others need the search."""
        a, b = self.head[i], self.head[j]
        out = np.where(a < b, -1, 1)
        near = np.flatnonzero(a == b)
        p, q = i[near], j[near]
        powers, p_end, q_end = self.powers, self.p[p + self.most], self.p[q + self.most]
        differ = (p_end - self.p[p]) * powers[p] != (q_end - self.p[q]) * powers[q]
        out[near[~differ]] = 0
        near, p, q = near[differ], p[differ], q[differ]
        got = self.common(p, q)
        out[near] = np.where(self.data[p + got] < self.data[q + got], -1, 1)
        return out

    def sorted(self, at: np.ndarray, group: np.ndarray) -> np.ndarray:
        """`at` sorted inside each group (groups stand together): all groups' runs are merged level by level at once."""
        at = at.copy()
        first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
        size = np.diff(np.r_[first, len(at)])
        begin, total = np.repeat(first, size), np.repeat(size, size)
        place = np.arange(len(at)) - begin
        level = 1
        while level < size.max():
            run = place // level
            other = (run ^ 1) * level
            length = np.minimum(level, total - other)
            place2 = place.copy()
            todo = np.flatnonzero((length > 0) & (total > level))
            for k in range(0, len(todo), AT_ONCE):
                mine = todo[k : k + AT_ONCE]
                low, high = np.zeros(len(mine), np.int64), length[mine]
                left = run[mine] % 2 == 0
                base = begin[mine] + other[mine]
                while True:
                    open_ = np.flatnonzero(low < high)
                    if not len(open_):
                        break
                    mid = (low[open_] + high[open_]) // 2
                    sign = self.sign(at[base[open_] + mid], at[mine[open_]])
                    before = np.where(left[open_], sign < 0, sign <= 0)
                    low[open_] = np.where(before, mid + 1, low[open_])
                    high[open_] = np.where(before, high[open_], mid)
                place2[mine] = (run[mine] // 2) * 2 * level + place[mine] - run[mine] * level + low
            out = np.empty_like(at)
            out[begin + place2] = at
            at, level = out, level * 2
        return at

    def same(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Byte by byte."""
        out = np.empty(len(i), bool)
        step = np.arange(self.most)
        for k in range(0, len(i), 16384):
            out[k : k + 16384] = (self.data[i[k : k + 16384, None] + step] == self.data[j[k : k + 16384, None] + step]).all(1)
        return out


def repeated_starts(keys: np.ndarray, data: np.ndarray, bounds: np.ndarray, window: int, gram: int) -> np.ndarray:
    """Of differing blocks (rows of `bounds`, with their keys): the starts in `data` whose `window` bytes stand at another start too."""
    row = np.repeat(np.arange(len(bounds) - 1, dtype=np.int32), np.diff(bounds))[: max(0, len(data) - gram + 1)]
    suffixes = Suffixes(data, window)
    # where the key's hash stands next: only starts at the same distance from it can agree
    nearest = np.full(len(row), len(data), np.int32)
    for i in range(0, len(row), AT_ONCE):
        at = np.arange(i, min(i + AT_ONCE, len(row)))
        at = at[H.span(suffixes.p, at, at + gram) == keys[row[at]]]
        nearest[at] = at
    nearest = np.minimum.accumulate(nearest[::-1])[::-1]
    start = np.arange(len(row), dtype=np.int32)
    start = start[start + window <= bounds[row + 1]]
    _, key = np.unique(keys, return_inverse=True)
    group = key[row[start]] * (window + 1) + np.minimum(nearest[start] - start, window)
    del row, nearest
    order = np.argsort(group, kind="stable")
    start, group = start[order], group[order]
    alone = np.r_[True, group[1:] != group[:-1]] & np.r_[group[1:] != group[:-1], True]
    start, group = start[~alone], group[~alone]
    # groups are sorted some at a time
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]) if len(group) else np.zeros(0, np.int64)
    found = [np.zeros(0, np.int64)]
    for i, j in H.pieces(np.r_[first, len(group)], AT_ONCE):
        lo, hi = first[i], first[j] if j < len(first) else len(group)
        found.append(_repeated(suffixes, start[lo:hi].astype(np.int64), group[lo:hi]))
    return np.sort(np.concatenate(found))


def _repeated(suffixes: Suffixes, start: np.ndarray, group: np.ndarray) -> np.ndarray:
    """The starts of whole groups (that stand together) whose bytes another one of their group has."""
    start = suffixes.sorted(start, group)
    hit = np.zeros(len(start), bool)
    for k in range(0, len(start) - 1, AT_ONCE):
        i, j = start[k : k + AT_ONCE], start[k + 1 : k + 1 + AT_ONCE]
        i = i[: len(j)]
        like = group[k + 1 : k + 1 + len(j)] == group[k : k + len(j)]
        near = np.flatnonzero(like & (suffixes.common(i, j) >= suffixes.most))
        near = near[suffixes.same(i[near], j[near])] + k
        hit[near] = hit[near + 1] = True
    return start[hit]


def _ranges(starts: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Runs of neighbouring starts as byte ranges."""
    new = np.flatnonzero(np.r_[True, np.diff(starts) > 1])
    return starts[new], starts[np.r_[new[1:] - 1, len(starts) - 1]] + window


def _emit_sorted(window: int, gram: int):
    def solve(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch | None:
        data = np.frombuffer(b"".join(x[2] for x in rows), np.uint8)
        bounds = np.r_[0, np.cumsum([len(x[2]) for x in rows])]
        h, b = (np.array([x[i] for x in rows], np.int64) for i in (0, 1))
        starts = repeated_starts(h.view(H.U), data, bounds, window, gram)
        if not len(starts):
            return None
        s, e = _ranges(starts, window)  # starts of different rows are at least `window` apart
        row = np.searchsorted(bounds, s, "right") - 1
        return pa.RecordBatch.from_arrays([pa.array(h[row]), pa.array(b[row]), pa.array((s - bounds[row]).astype(np.int32)), pa.array((e - bounds[row]).astype(np.int32))], names=["h", "b", "s", "e"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held, last = [], 0, None
        for batch in batches:
            for h, b, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if (h, b) == last:  # a repeated row of the table
                    continue
                if held > 1 << 18 and h != last[0]:
                    if (out := solve(rows)) is not None:
                        yield out
                    rows, held = [], 0
                rows.append((h, b, x))
                held, last = held + len(x), (h, b)
        if rows and (out := solve(rows)) is not None:
            yield out

    return run


def _anchored(keys: np.ndarray, data: np.ndarray, bounds: np.ndarray, window: int, gram: int, p: np.ndarray) -> tuple[np.ndarray, ...]:
    """Row and start of each window of differing blocks, and the distance from it to where the key's hash stands next."""
    row = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))[: max(0, len(data) - gram + 1)]
    at = np.arange(len(row))
    nearest = np.where(H.span(p, at, at + gram) == keys[row], at, len(data))
    nearest = np.minimum.accumulate(nearest[::-1])[::-1]
    at = at[at + window <= bounds[row + 1]]
    return row[at], at, nearest[at] - at


def _emit_windows(window: int, gram: int):
    """Neighbouring windows with a part in common, in a row with that part's hash: two windows can only agree where that does."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, bounds = H.text_buffer(batch.column("bytes"))
            keys = batch.column("h").to_numpy().view(H.U)
            for i, j in H.pieces(bounds, 1 << 17):
                part, cut = data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i]
                p = H.prefix(part)
                row, at, far = _anchored(keys[i:j], part, cut, window, gram, p)
                if not len(at):
                    continue
                core = at + far % TOGETHER  # all windows that have it end behind it
                first = np.flatnonzero(np.r_[True, (core[1:] != core[:-1]) | (row[1:] != row[:-1])])
                each = np.stack([H.span(p, at, at + window), verifiers(part, at, at + window)], 1)
                c = core[first]
                take = pa.array(row[first] + i)
                s = (at - cut[row])[first].astype(np.int32)
                yield pa.RecordBatch.from_arrays([H.longs(H.span(p, c, c + window - TOGETHER + 1)), batch.column("h").take(take), batch.column("b").take(take), pa.array(s), H.binary(each.reshape(-1).view(np.uint8), np.r_[first, len(at)] * 16)], names=["x", "h", "b", "s", "w"])

    return run


def _emit_repeated(window: int):
    """Rows of windows in the order of (x, w): the ranges whose windows stand in another row too. Equal rows are held once."""

    def solve(held: list[list]) -> Iterator[tuple[int, int, int, int]]:
        size = np.array([len(x[3]) // 16 for x in held])
        each = np.frombuffer(b"".join(x[3] for x in held), H.U).reshape(-1, 2)
        of = np.repeat(np.arange(len(held)), size)
        order = np.lexsort((each[:, 1], each[:, 0]))
        same = (each[order[1:]] == each[order[:-1]]).all(1)
        hit = np.array([x[4] for x in held])[of]
        hit[order[1:][same]] = hit[order[:-1][same]] = True
        begin = np.cumsum(size) - size
        found = np.flatnonzero(hit)
        new = np.flatnonzero(np.r_[True, (np.diff(found) > 1) | (of[found[1:]] != of[found[:-1]])]) if len(found) else found
        for k, last in zip(found[new].tolist(), found[np.r_[new[1:] - 1, len(found) - 1]].tolist() if len(found) else [], strict=True):
            h, b, s = held[of[k]][:3]
            at = s + k - int(begin[of[k]])
            yield h, b, at, at + last - k + window

    def batch_of(rows: list[tuple[int, int, int, int]]) -> pa.RecordBatch:
        h, b, s, e = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(b, pa.int64()), pa.array(s, pa.int32()), pa.array(e, pa.int32())], names=["h", "b", "s", "e"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list] = []
        last = None
        for batch in batches:
            out = []
            for x, h, b, s, w in zip(*(batch.column(c).to_pylist() for c in ("x", "h", "b", "s", "w")), strict=True):
                if x != last and len(held) >= 4096:
                    out += solve(held)
                    held = []
                if x == last and held and held[-1][3] == w:
                    held[-1][4] = True
                    out.append((h, b, s, s + len(w) // 16 - 1 + window))
                else:
                    held.append([h, b, s, w, False])
                last = x
            if out:
                yield batch_of(out)
        if held and (out := list(solve(held))):
            yield batch_of(out)

    return run


def keyed(docs: DataFrame) -> DataFrame:
    """Rows as the operator sees them: `mark` tells texts with the same id apart."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"), F.col("text"))


def repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, wide_key: int = WIDE_KEY) -> DataFrame:
    """doc_id, mark, spans: an array of byte ranges (s, e) of each text that repeat elsewhere; ranges may overlap."""
    texts = keyed(docs)
    blocks = store(texts.where(F.octet_length("text") >= window).mapInArrow(H.tidy(_emit_blocks(window, gram)), _BLOCKS), "all-blocks")
    keys = blocks.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min("b").alias("b0"), F.max("b").alias("b1"), F.max("again").alias("a")).where("c > 1 or a")
    # one block alone is mixed if its key's hash stands in it twice; blocks that are all alike never are
    keys = keys.select("h", ((F.col("c") == 1) | (F.col("b0") != F.col("b1"))).alias("mixed"))
    # kept apart, so that a key with very many blocks is dealt to several tasks
    found = store(blocks.drop("again").join(store(keys, "keys"), "h"), "blocks")

    one = found.where("mixed").groupBy("h", "b").agg(F.min(F.struct("doc_id", "mark", "lo", "n")).alias("at"), (F.count(F.lit(1)) > 1).alias("twice"))
    per_key = one.groupBy("h").agg(F.count(F.lit(1)).alias("k"), F.sum(F.col("at.n") + (window - 1)).alias("bytes"))
    asked = one.join(per_key, "h").select("h", "b", "at.*", "twice", ((F.col("k") > wide_key) | (F.col("bytes") > WIDE_BYTES)).alias("wide"))
    asked = store(asked, "asked")

    def contexts(which: str) -> DataFrame:
        lists = asked.where(which).groupBy(F.col("doc_id").alias("d"), F.col("mark").alias("m")).agg(F.collect_list(F.struct("h", "b", "lo", "n")).alias("asked"))
        there = texts.join(lists, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m")))
        return there.select("text", "asked").mapInArrow(H.tidy(_emit_contexts(window)), _CONTEXTS)

    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranges = contexts("not wide").repartition(n, "h").sortWithinPartitions("h", "b").mapInArrow(H.tidy(_emit_sorted(window, gram)), _RANGES)
    if not asked.where("wide").isEmpty():
        windows = contexts("wide").mapInArrow(H.tidy(_emit_windows(window, gram)), "x long, h long, b long, s int, w binary")
        ranges = ranges.unionByName(windows.repartition(n, "x").sortWithinPartitions("x", "w").mapInArrow(H.tidy(_emit_repeated(window)), _RANGES))
    # the sort sees each different block once: what stands in several places is a copy as a whole, the others stand where they were asked for
    copies = found.where("mixed").join(asked.where("twice").select("h", "b"), ["h", "b"], "left_semi")
    whole = found.where("not mixed").select("doc_id", "mark", "lo", "n").unionByName(copies.select("doc_id", "mark", "lo", "n"))
    whole = whole.select("doc_id", "mark", F.col("lo").alias("s"), (F.col("lo") + F.col("n") + (window - 1)).alias("e"))
    parts = asked.where("not twice").join(ranges, ["h", "b"]).select("doc_id", "mark", (F.col("lo") + F.col("s")).alias("s"), (F.col("lo") + F.col("e")).alias("e"))
    return whole.unionByName(parts).groupBy("doc_id", "mark").agg(F.collect_list(F.struct("s", "e")).alias("spans"))


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs of bytes: ranges that touch or overlap become one."""
    out: list[list[int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [(s, e) for s, e in out]


def kept(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    at, out = 0, []
    for s, e in spans:
        out.append(text[at:s])
        at = e
    out.append(text[at:])
    return b"".join(out)


def inside_characters(text: bytes, spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ranges drawn in to whole UTF-8 characters, so that what stays is text."""
    out = []
    for s, e in spans:
        while s < e and text[s] & 0xC0 == 0x80:
            s += 1
        while e > s and e < len(text) and text[e] & 0xC0 == 0x80:
            e -= 1
        if s < e:
            out.append((s, e))
    return out


def _apply(with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = batch.schema.names
            extra = [x for x in names if x not in ("text", "spans", "doc_id")]
            n_bytes, n_removed, n_spans, sha, texts = [], [], [], [], []
            for text, spans in zip(batch.column("text"), batch.column("spans"), strict=True):
                text, spans = text.as_py(), spans.as_py()
                raw = (text or "").encode()
                runs = merged([(x["s"], x["e"]) for x in spans or ()])
                n_bytes.append(len(raw))
                n_removed.append(sum(e - s for s, e in runs))
                n_spans.append(len(runs))
                sha.append(hashlib.sha256(kept(raw, runs)).hexdigest())
                if with_text:
                    texts.append(kept(raw, inside_characters(raw, runs)).decode() if runs else text)
            out = [batch.column("doc_id"), pa.array(n_bytes, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(sha, pa.string())]
            cols = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
            if with_text:
                out, cols = [*out, pa.array(texts, pa.string()), *(batch.column(x) for x in extra)], [*cols, "text", *extra]
            yield pa.RecordBatch.from_arrays(out, names=cols)

    return run


_DIGEST = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remove_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, with_text: bool = False) -> DataFrame:
    """Digest of each document without its repeated bytes; `with_text` adds what is left as text (whole characters)."""
    spans = repeats(docs, window, gram).select(F.col("doc_id").alias("d"), F.col("mark").alias("m"), "spans")
    both = keyed(docs).join(spans, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m")), "left")
    return both.select("doc_id", "text", "spans").mapInArrow(H.tidy(_apply(with_text)), _DIGEST + (", text string" if with_text else ""))


def without_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """`docs` with repeated passages taken out of `text`; all columns and rows stay."""
    spans = repeats(docs, window)
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("d"), F.xxhash64("text").alias("m"))
    hit = rows.join(spans, F.col("d").eqNullSafe(F.col("doc_id")) & (F.col("m") == F.col("mark")), "left")
    text = F.udf(_cut, "string", useArrow=True)("row.text", "spans")
    return hit.select(*[text.alias(c) if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns])


def _cut(text: str | None, spans: list | None) -> str | None:
    if text is None or not spans:
        return text
    raw = text.encode()
    return kept(raw, inside_characters(raw, merged([(x["s"], x["e"]) for x in spans]))).decode()
