"""Benchmark items in documents: SimHash windows of an item's size, found by multi-index Hamming search.

Texts are lower-cased in A-Z and cut into words; items and windows are multisets of `k`-word shingles. A
window has as many shingles as the item (the whole document, if that has fewer). A window that holds too few
shingles of any item at all can't be as similar as asked to one; all others are fingerprinted. A fingerprint has
64 bits, each the sign of a sum over shingles weighted by how often they stand. The items of a size are indexed by
eight blocks of their fingerprints: within a Hamming radius of 23 at least one block differs in two bits at
most, and lookups of all such block values find every item within the radius. These are the candidates; they are
confirmed by the weighted Jaccard similarity of the shingles, sum of minima over sum of maxima of their counts.

Two multisets at similarity 0.8 differ in a bit with probability 0.15; more than 23 of 64 bits differ for
about one pair in 96,000. Null and empty texts match nothing, nor do items without words. Items of
fewer than `k` words are one shingle, compared with every run of as many words. Repeated rows, rows with one id and
rows without id are looked at one by one. Extra columns are ignored, whatever their names. Very long texts are
fingerprinted in parts of BLOCK windows. Items go to the executors in packs of at most PACK bytes; the benchmark
has to fit the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H

RADIUS, BLOCKS = 23, 8
#: Items are sent to the executors in packs of at most so many bytes of text.
PACK = 4 << 20
#: Windows that are fingerprinted at once.
BLOCK = 1 << 15
_BITS = np.arange(64, dtype=H.U)
_ONES = np.array([bin(i).count("1") for i in range(256)], np.uint8)
_RESULT = "doc_id long, item_id long, similarity double, hamming int, first_word int, n_words int, n_windows int"


def signs(shingles: np.ndarray) -> np.ndarray:
    """+1 or -1 for each bit of each shingle's hash."""
    return ((H.mix(shingles)[:, None] >> _BITS & H.U(1)).astype(np.int32) << 1) - 1


def fingerprint(total: np.ndarray) -> np.ndarray:
    """Bits of the sums; a sum of 0 counts as set."""
    return ((total >= 0).astype(H.U) << _BITS).sum(-1, dtype=H.U)


def hamming(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return _ONES[np.bitwise_xor(a, b).reshape(-1, 1).view(np.uint8)].sum(1)


class MultiIndex:
    """Fingerprints by blocks of bits; `near` finds all within the radius."""

    def __init__(self, prints: np.ndarray, radius: int = RADIUS):
        self.prints, self.radius = prints, radius
        values = np.arange(256)
        close = _ONES[values[:, None] ^ values[None, :]] <= radius // BLOCKS
        blocks = prints.reshape(-1, 1).view(np.uint8)
        # for each block and each value it may have: the fingerprints that lie near in this block
        lists = [np.flatnonzero(close[v][blocks[:, b]]) for b in range(BLOCKS) for v in values]
        self.ends = np.r_[0, np.cumsum([len(x) for x in lists])]
        self.items = np.concatenate(lists)

    def near(self, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number of the fingerprint asked for, number of the indexed one) of all pairs within the radius, in order."""
        n, size = len(asked), len(self.prints)
        cell = asked.reshape(-1, 1).view(np.uint8).astype(np.int64) + 256 * np.arange(BLOCKS)
        first, many = self.ends[cell].ravel(), (self.ends[cell + 1] - self.ends[cell]).ravel()
        found = []
        for i, j in H.pieces(np.r_[0, np.cumsum(many)], 1 << 20):
            m = many[i:j]
            at = np.repeat(first[i:j] - np.cumsum(m) + m, m) + np.arange(m.sum())
            pair = np.repeat(np.arange(i, j) // BLOCKS, m) * size + self.items[at]
            pair = np.unique(pair)
            found.append(pair[hamming(asked[pair // size], self.prints[pair % size]) <= self.radius])
        pair = np.unique(np.concatenate(found)) if n and found else np.zeros(0, np.int64)
        return pair // max(size, 1), pair % max(size, 1)


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """Sum of minima and sum of maxima of the counts of two multisets."""
    values, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
    p = np.bincount(inverse[: len(a)], minlength=len(values))
    q = np.bincount(inverse[len(a) :], minlength=len(values))
    return int(np.minimum(p, q).sum()), int(np.maximum(p, q).sum())


class Items:
    """A pack of items of one shingle width."""

    def __init__(self, ids: list[int], texts: list[str], k: int, width: int, percent: int):
        """Items of at least `k` words if width == k, else those of exactly `width` words."""
        data, bounds = H.text_buffer(pa.array(texts, pa.string()))
        data = H.LOWER[data]
        lo, hi, row = H.words(data, bounds)
        count = np.bincount(row, minlength=len(ids))
        rows, values = run_hashes(data, lo, hi, row, width)
        mine = (count >= k) if width == k else (count == width)
        self.percent, self.width = percent, width
        self.ids = [ids[i] for i in np.flatnonzero(mine)]
        self.sets = [values[rows == i] for i in np.flatnonzero(mine)]
        self.size = np.array([len(s) for s in self.sets], np.int64)
        owner = np.repeat(np.arange(len(self.sets)), self.size)
        flat = np.concatenate(self.sets) if self.sets else np.zeros(0, H.U)
        owner, flat = H.distinct(owner, flat)
        order = np.argsort(flat, kind="stable")
        self.owner = owner[order]
        self.keys, self.first = np.unique(flat[order], return_index=True)
        self.ends = np.r_[self.first[1:], len(flat)]
        self.member = owner * len(self.keys) + np.searchsorted(self.keys, flat)  # (item, key), sorted
        self.prints = np.array([fingerprint(signs(s).sum(0)) for s in self.sets], H.U)
        self.by_size = {int(n): (at, MultiIndex(self.prints[at])) for n in np.unique(self.size) for at in [np.flatnonzero(self.size == n)]}

    def search(self, values: np.ndarray, rows: np.ndarray, n: int) -> list[tuple]:
        """(row, item, similarity, hamming, first shingle, shingles, windows) for runs of shingles of n texts."""
        if not len(self.keys) or not len(values):
            return []
        at = np.minimum(np.searchsorted(self.keys, values), len(self.keys) - 1)
        key = np.where(self.keys[at] == values, at, -1)
        begin, end = np.searchsorted(rows, np.arange(n)), np.searchsorted(rows, np.arange(n), "right")
        held = np.r_[0, np.cumsum(key >= 0)]
        best: dict[tuple[int, int], list] = {}
        for size in self.by_size:
            window = np.minimum(size, end - begin)
            # 100 * common >= percent * (sizes - common), with common at most the places that hold shingles of any item
            least = -(-self.percent * (size + window) // (100 + self.percent))
            for r in np.flatnonzero((held[end] - held[begin] >= least) & (least <= window)):
                start = np.arange(begin[r], end[r] - window[r] + 1)
                start = start[held[start + window[r]] - held[start] >= least[r]]
                for i in range(0, len(start), BLOCK):
                    self._windows(values, key, start[i : i + BLOCK], int(window[r]), size, best, int(r), int(begin[r]))
        return [(r, self.ids[item], b[0], b[2], -b[1], b[3], b[4]) for (r, item), b in sorted(best.items())]

    def _windows(self, values: np.ndarray, key: np.ndarray, start: np.ndarray, window: int, size: int, best: dict, row: int, begin: int) -> None:
        """Looks the windows at `start` up and keeps the best of those that are similar enough to an item of `size` shingles."""
        prints = np.empty(len(start), H.U)
        for i, j in _stretches(start, window):
            base = int(start[i])
            sums = np.zeros((int(start[j - 1]) + window - base + 1, 64), np.int32)
            np.cumsum(signs(values[base : base + len(sums) - 1]), axis=0, out=sums[1:])
            prints[i:j] = fingerprint(sums[start[i:j] + window - base] - sums[start[i:j] - base])
        items, index = self.by_size[size]
        asked, found = index.near(prints)
        item = items[found]
        for i in range(0, len(asked), max(1, (1 << 20) // window)):
            a, b = asked[i : i + max(1, (1 << 20) // window)], item[i : i + max(1, (1 << 20) // window)]
            keys = key[start[a][:, None] + np.arange(window)]
            pair = np.where(keys >= 0, b[:, None] * len(self.keys) + keys, -1)
            place = np.minimum(np.searchsorted(self.member, pair), len(self.member) - 1)
            common = (self.member[place] == pair).sum(1)  # at least as many as the sum of minima
            for x in np.flatnonzero(100 * common >= self.percent * (size + window - common)):
                s, what = int(start[a[x]]), int(b[x])
                low, high = weighted_jaccard(values[s : s + window], self.sets[what])
                if 100 * low >= self.percent * high:
                    here = [low / high, begin - s, int(hamming(prints[a[x] : a[x] + 1], self.prints[what : what + 1])[0]), window]
                    there = best.get((row, what))
                    best[row, what] = [*(max(there[:4], here) if there else here), there[4] + 1 if there else 1]


def _stretches(start: np.ndarray, window: int) -> Iterator[tuple[int, int]]:
    """Runs of starts that lie close enough to share sums."""
    cut = np.flatnonzero(np.diff(start) > window) + 1
    return zip(np.r_[0, cut].tolist(), np.r_[cut, len(start)].tolist(), strict=True)


def run_hashes(data: np.ndarray, lo: np.ndarray, hi: np.ndarray, row: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, hash) of every run of k words."""
    if len(lo) < k:
        return np.zeros(0, np.int64), np.zeros(0, H.U)
    word = H.span(H.prefix(data), lo, hi)
    run = word[: len(word) - k + 1].copy()
    for i in range(1, k):
        run = H.mix(run * H.U(0x100000001B3) + word[i : len(word) - k + 1 + i])
    whole = row[: len(word) - k + 1] == row[k - 1 :]
    return row[: len(word) - k + 1][whole], run[whole]


def _found(packs: list[Items], column: pa.Array) -> Iterator[tuple]:
    """(row, item, similarity, hamming, first word, words, windows) for each text and item that match."""
    data, bounds = H.text_buffer(column)
    for i, j in H.pieces(bounds):
        part = H.LOWER[data[bounds[i] : bounds[j]]]
        lo, hi, row = H.words(part, bounds[i : j + 1] - bounds[i])
        for items in packs:
            rows, values = run_hashes(part, lo, hi, row, items.width)
            for r, item, s, h, f, w, n in items.search(values, rows, j - i):
                yield i + r, item, s, h, f, w + items.width - 1, n


def _search(packs: list[Items]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id")
            out = [(ids[r].as_py(), *found) for r, *found in _found(packs, batch.column("text"))]
            types = (pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.int32(), pa.int32())
            cols = list(zip(*out, strict=True)) or [[]] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["doc_id", "item_id", "similarity", "hamming", "first_word", "n_words", "n_windows"])

    return run


def _clean(packs: list[Items], place: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = np.ones(batch.num_rows, bool)
            keep[[r for r, *_ in _found(packs, batch.column(place))]] = False
            yield batch.filter(pa.array(keep))

    return run


def _packs(benchmark: DataFrame, k: int, percent: int) -> Iterator[list[Items]]:
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    size = int(items.agg(F.sum(F.octet_length("text"))).first()[0] or 0)
    packs = max(1, -(-size // PACK))
    for p in range(packs):  # one pass for each pack, however large the benchmark is
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(packs)) == p).collect()
        ids, bodies = [r["item_id"] for r in rows], [r["text"] for r in rows]
        yield [x for x in (Items(ids, bodies, k, w, percent) for w in range(1, k + 1)) if x.ids]


def matches(docs: DataFrame, benchmark: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """A row for each document and item that match: the most similar window and how many windows match."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = None
    for pack in _packs(benchmark, k, percent):
        here = texts.mapInArrow(H.tidy(_search(pack)), _RESULT)
        found = here if found is None else found.unionByName(here)
    return found


def without_matches(docs: DataFrame, benchmark: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """`docs` without the rows whose text matches an item; each is looked at where it stands, nothing is joined."""
    out = docs
    for pack in _packs(benchmark, k, percent):
        out = out.mapInArrow(H.tidy(_clean(pack, docs.columns.index("text"))), docs.schema)
    return out
