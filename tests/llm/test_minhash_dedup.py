import random
import re

import numpy as np
import pyarrow as pa
import pytest

from bedvoids.llm import minhash_dedup as M

SCHEMA = "doc_id long, text string, x int, rep string"


def shingles(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()


def brute(rows, k):
    sets = [shingles(t, k) for _, t in rows]
    up = list(range(len(rows)))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 100 * len(a & b) >= 80 * len(a | b):
                up[max(top(i), top(j))] = min(top(i), top(j))
    least = {}
    for i, (d, _) in enumerate(rows):
        least[top(i)] = min(least.get(top(i), d), d)
    return sorted((d, len(sets[i]), least[top(i)], d == least[top(i)]) for i, (d, _) in enumerate(rows))


def made(seed):
    r = random.Random(seed)
    vocabulary = ["w%d" % i for i in range(300)] + ["Über", "É x", "A|b"]
    rows = [(0, None), (1, ""), (2, " \t\n"), (3, "one"), (4, "ONE"), (5, "one two"), (6, "one  two\n"), (7, "one two three four five six"), (8, "one two three four five")]
    for i in range(9, 160):
        if r.random() < 0.6 and i > 12:
            w = (rows[r.randrange(9, i)][1]).split(" ")
            for _ in range(r.choice([0, 1, 1, 2, 3, 6])):
                w[r.randrange(len(w))] = r.choice(vocabulary)
        else:
            w = [r.choice(vocabulary) for _ in range(r.choice([3, 10, 40, 80]))]
        rows.append((i, " ".join(w)))
    rows += [(160, rows[30][1] + " " + rows[30][1]), (161, rows[40][1]), (161, rows[41][1])]
    return rows


def test_against_all_pairs(spark):
    for seed, k in ((1, 2), (2, 5), (3, 2)):
        rows = made(seed)
        df = spark.createDataFrame([(*x, 1, "r") for x in rows], SCHEMA).repartition(3)
        got = sorted(map(tuple, M.groups(df, k).collect()))
        assert got == brute(rows, k)


def test_texts_of_one_id_are_apart(spark):
    a, b = (" ".join(f"{c}{i}" for i in range(40)) for c in "ab")
    rows = [(1, a + " more"), (2, a), (2, b), (2, b), (None, a), (None, b), (5, ""), (5, "")]
    df = spark.createDataFrame([(*x, 7, "h", True) for x in rows], "doc_id long, text string, _row int, mark string, _kept boolean")
    got = sorted(map(tuple, M.groups(df).select("doc_id", "component_id", "kept").collect()), key=str)
    assert got == sorted([(1, 1, True), (2, 1, False), (2, 2, True), (2, 2, True), (None, None, True), (None, None, True), (5, 5, True), (5, 5, True)], key=str)
    out = M.one_of_each(df)
    assert out.columns == df.columns
    assert sorted(map(tuple, out.select("doc_id", "text").collect()), key=str) == sorted([(1, a + " more"), (2, b), (None, a), (None, b), (5, "")], key=str)


def test_one_of_each(spark):
    text = " ".join("word%d" % i for i in range(40))
    df = spark.createDataFrame([(3, text, 1, "a"), (2, text + " more", 2, "b"), (9, "other text here", 3, "c"), (5, None, 4, "d"), (None, "x", 5, "e")], SCHEMA)
    out = M.one_of_each(df)
    assert out.columns == df.columns
    assert sorted(x.rep for x in out.collect()) == ["b", "c", "d", "e"]


def test_empty_table(spark):
    assert M.groups(spark.createDataFrame([], SCHEMA)).count() == 0


@pytest.mark.parametrize("blocks", [1, 2])
def test_pairs_that_a_bound_leaves_against_plain_loops(blocks):
    r = np.random.default_rng(blocks)
    m = 700
    c = r.integers(0, 4, (m, M.PARTS)).astype(np.int32)
    c[:200] = c[0] + (r.random((200, M.PARTS)) < 0.1)
    n, g, at = c.sum(1) + r.integers(0, 9, m), np.where(np.arange(m) < 150, 7, np.arange(m)), np.arange(m) % blocks
    rep = r.permutation(m)
    part = pa.table({"i": np.zeros(m, np.int32), "j": np.full(m, blocks - 1, np.int32), "at": at.astype(np.int32), "rep": rep, "n": n, "g": g, "c": list(c)})
    size, many = n.tolist(), np.minimum(c[:, None, :200], c[None]).sum(2)
    want = set()
    for a in range(m):
        for b in range(a):
            if g[a] != g[b] and (blocks == 1 or at[a] != at[b]) and min(size[a], size[b]) * 100 >= 80 * max(size[a], size[b]) and many[a, b] * 180 >= 80 * (size[a] + size[b]):
                want.add((min(rep[a], rep[b]), max(rep[a], rep[b])))
    got = list(zip(*(x.tolist() for x in M.bounded(part, 80)), strict=True))
    assert len(want) > 500 and len(got) == len(set(got)) and set(got) == want


def test_buckets_in_blocks(spark, monkeypatch):
    rows = made(5)
    monkeypatch.setattr(M, "BLOCK", 3)
    got = M.groups(spark.createDataFrame([(*x, 0, "") for x in rows], SCHEMA), k=2).select("doc_id", "n_shingles", "component_id", "kept")
    assert sorted(map(tuple, got.collect())) == brute(rows, 2)


def test_texts_that_nobody_asks_for_are_not_shuffled(spark):
    texts = spark.range(-1000, 4000).selectExpr("nullif(id, -1000) AS doc_id", "xxhash64(id) AS mark", "cast(id AS string) AS text")
    asked = texts.where("doc_id % 20 = 0").selectExpr("doc_id AS rep", "struct(doc_id, mark) AS head")
    got = M.likely(texts, asked)
    ids = {r.doc_id for r in got.collect()}
    assert got.columns == texts.columns and {r.rep for r in asked.collect()} <= ids and len(ids) < 1200
    assert M.likely(texts, asked.where("false")).isEmpty()


@pytest.mark.parametrize("size", [1, 2, 3, 7, 500])
def test_buckets_of_several_nodes_from_rows_in_order(size):
    r = np.random.default_rng(size)
    key, rep = np.sort(r.integers(-60, 60, 150)), np.zeros(150, np.int64)
    for k in set(key.tolist()):
        rep[key == k] = np.sort(r.permutation(1000)[: (key == k).sum()])
    rows = list(zip(key.tolist(), rep.tolist(), (rep % 7 + 1).tolist(), strict=True))
    want = []
    for k, a, n in rows:
        bucket = [x for x in rows if x[0] == k]
        if len(bucket) > 1:
            want.append((k, a, n, bucket[0][1], bucket[0][2]))
    table = pa.table(dict(zip(("key", "rep", "n"), zip(*rows, strict=True), strict=True)))
    got = [tuple(x.values()) for batch in M._emit_members(iter(table.to_batches(max_chunksize=size))) for x in batch.to_pylist()]
    assert 0 < len(want) < 150 and got == want
    words = [b.rename_columns(["word", "rep", "n"]) for b in table.to_batches(max_chunksize=size)]
    assert [tuple(x.values()) for batch in M._emit_shared(iter(words)) for x in batch.to_pylist()] == [(a, k % M.PARTS) for k, a, *_ in want]


def test_a_set_is_sent_once_for_each_pair(spark):
    pairs = [(1, b) for b in range(2, 202)] + [(2, 3)]
    rows = M.addressed(spark.createDataFrame(pairs, "a long, b long")).collect()
    hubs = [r for r in rows if r.side == 0]
    assert sorted((r.a, r.rep) for r in rows if r.side == 1) == sorted(pairs)
    assert 2 <= len(hubs) <= 1 + -(-200 // M.SHARE) and all(r.rep == r.a for r in hubs)
    assert {(r.a, r.salt) for r in hubs} == {(r.a, r.salt) for r in rows if r.side == 1}


def test_bands_do_not_stay_on_disk(spark, monkeypatch, tmp_path):
    from bedvoids.sources import shared

    monkeypatch.setattr(shared, "shared_dir", lambda spark: str(tmp_path / "a folder"))
    rows = made(6)
    got = M.groups(spark.createDataFrame([(*x, 0, "") for x in rows], SCHEMA), k=2)
    stay = [f for f in (tmp_path / "a folder" / "bedvoids").iterdir() if any(f.glob("*.parquet"))]
    assert stay and not [f.name for f in stay if "bands" in spark.read.parquet(str(f)).columns]
    assert sorted(map(tuple, got.collect())) == brute(rows, 2)
