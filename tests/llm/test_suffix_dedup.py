import hashlib
import random
import tracemalloc

import numpy as np
import pytest

from bedvoids.llm import suffix_dedup as S
from bedvoids.llm import texthash as H

SCHEMA = "doc_id long, text string"


def brute(rows, window=200):
    raw = [(t or "").encode() for _, t in rows]
    starts = {}
    for d, x in enumerate(raw):
        for i in range(len(x) - window + 1):
            starts.setdefault(x[i : i + window], []).append((d, i))
    gone = [bytearray(len(x)) for x in raw]
    for where in starts.values():
        if len(where) > 1:
            for d, i in where:
                gone[d][i : i + window] = b"\1" * window
    out = []
    for (doc_id, _), x, g in zip(rows, raw, gone, strict=True):
        runs = sum(1 for i in range(len(g)) if g[i] and (i == 0 or not g[i - 1]))
        out.append((doc_id, len(x), sum(g), runs, hashlib.sha256(bytes(c for c, k in zip(x, g, strict=True) if not k)).hexdigest()))
    return sorted(out)


def made(seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdeé") for _ in range(r.randint(1, 7)))
    prose = lambda n: " ".join(word() for _ in range(n))
    shared = [prose(n) for n in (30, 60, 120, 300, 38, 39, 40, 41)]
    rows = [(0, None), (1, ""), (2, "x" * 150), (3, "x" * 500), (4, "ab" * 300), (5, "x" * 230), (6, prose(3000))]
    for i in range(7, 60):
        parts = [prose(r.randint(0, 80)) for _ in range(3)]
        for _ in range(r.randint(0, 3)):
            s = r.choice(shared)
            a = r.randint(0, len(s) // 2)
            parts.insert(r.randint(0, len(parts)), s[a : a + r.randint(50, len(s))])
        rows.append((i, "|".join(parts)))
    rows += [(60, rows[20][1]), (61, rows[20][1] + "!"), (61, "again"), (62, shared[3] + shared[3])]
    return rows


@pytest.mark.parametrize("seed", [1, 2])
@pytest.mark.parametrize("wide", [2000, 3])
def test_against_all_substrings(spark, seed, wide, monkeypatch):
    rows = made(seed)
    monkeypatch.setattr(S.repeats, "__defaults__", (200, 64, wide))
    got = sorted(map(tuple, S.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5)).collect()))
    assert got == brute(rows)


def test_text_stays_text(spark):
    rows = [(1, "é" * 300 + "tail one"), (2, "head" + "é" * 300), (3, None)]
    df = spark.createDataFrame([(*x, "k", 7, "s", 1, 2) for x in rows], SCHEMA + ", h string, b int, spans string, _row_mark int, mark int")
    out = S.without_repeats(df)
    assert out.columns == df.columns and [tuple(r)[2:] for r in out.collect()] == [("k", 7, "s", 1, 2)] * 3
    assert sorted((x.doc_id, x.text) for x in out.collect()) == [(1, "tail one"), (2, "head"), (3, None)]


def test_empty_table(spark):
    assert S.remove_repeats(spark.createDataFrame([], SCHEMA)).count() == 0


def _noise(seed, n):
    r = random.Random(seed)
    return "".join(r.choice("abcdefghijklmnopqrstuvwxyz ") for _ in range(n))


def _copies():
    """Exact copies beside a near copy of one changed byte or word, and exact copies of a line that stands several times in a row."""
    out = []
    for seed in range(8):
        text = _noise(seed, 900)
        near = text[:450] + "#" + text[451:] if seed % 2 else text[:450] + " another " + text[460:]
        out.append([text, text, near])
    for width in (64, 80, 100, 136):
        text = _noise(width, 300) + (_noise(width + 1, width - 1) + "\n") * 4 + _noise(width + 2, 300)
        out += [[text, text], [text, text, text.replace("\n", "\t", 1)]]
    return out


@pytest.mark.parametrize("wide", [2000, 1])
def test_exact_copies_beside_near_ones_and_repeated_lines(spark, wide, monkeypatch):
    monkeypatch.setattr(S.repeats, "__defaults__", (200, 64, wide))
    rows = [(i, t) for i, t in enumerate(t for group in _copies() for t in group)]
    rows += [(len(rows), rows[3][1]), (3, rows[3][1])]
    got = sorted(map(tuple, S.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5)).collect()))
    assert got == brute(rows)


def test_many_bytes_of_one_key_are_sorted_in_little_memory():
    r = random.Random(4)
    line = "".join(r.choice("abcdefgh") for _ in range(90))
    rows = [("%05d" % i * 30 + line * 20 + "%05d" % i * 9).encode() for i in range(270)]
    data, bounds = np.frombuffer(b"".join(rows), np.uint8), np.cumsum([0, *map(len, rows)])
    at = np.array([150])
    keys = np.repeat(H.span(H.prefix(data[: len(rows[0])]), at, at + 64), len(rows))
    tracemalloc.start()
    got = S.repeated_starts(keys, data, bounds, 200, 64)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    # windows that begin in front of the lines or end behind them are each row's own
    assert set(got - bounds[np.searchsorted(bounds, got, "right") - 1]) >= set(range(150, 150 + 90 * 18 - 20)) and peak < 200 * len(data)


def test_keys_with_many_bytes_over_the_cluster(spark, monkeypatch):
    rows = made(3)
    monkeypatch.setattr(S, "WIDE_BYTES", 700)
    assert sorted(map(tuple, S.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5)).collect())) == brute(rows)


@pytest.mark.parametrize("wide", [2000, 1])
def test_copies_of_a_block_are_not_paired_with_its_windows(spark, wide):
    text = _noise(31, 4000)
    near = [text[: 70 * i] + "#%d#" % i + text[70 * i :] for i in range(1, 50)]
    rows = list(enumerate([text] * 40 + near))
    spans = S.repeats(spark.createDataFrame(rows, SCHEMA).repartition(5), wide_key=wide).collect()
    blocks = {r.doc_id: r.n for r in spark.createDataFrame(rows, SCHEMA).select("doc_id", S.F.lit(0).cast("long").alias("mark"), "text").mapInArrow(S._emit_blocks(200, 64), S._BLOCKS).groupBy("doc_id").agg(S.F.count("*").alias("n")).collect()}
    # copies once a block, others once for each run of neighbouring windows
    assert all(len(r.spans) <= blocks[r.doc_id] for r in spans if r.doc_id < 40)
    assert sum(len(r.spans) for r in spans) < 2 * sum(blocks.values())
    got = sorted(map(tuple, S.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5)).collect()))
    assert got == brute(rows)


def test_windows_that_go_together_over_the_cluster(spark, monkeypatch):
    rows = made(5)
    rows += [(100 + i, x) for i, x in enumerate(t for group in _copies() for t in group)]
    monkeypatch.setattr(S.repeats, "__defaults__", (200, 64, 0))
    assert sorted(map(tuple, S.remove_repeats(spark.createDataFrame(rows, SCHEMA).repartition(5)).collect())) == brute(rows)
