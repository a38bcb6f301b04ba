import numpy as np

from bedvoids.llm import cover_tree as C

SCHEMA = "vec_id long, embedding array<float>, label int, unit string, m int"


def brute(rows, cosine=0.9):
    ok = {}
    for i, v in enumerate(rows):
        x = None if v[1] is None else np.array([np.nan if y is None else y for y in v[1]], np.float32).astype(float)
        if x is not None and len(x) and np.isfinite(x).all() and x.any():
            ok[i] = x / np.linalg.norm(x)
    up = list(range(len(rows)))

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    n = [0] * len(rows)
    for i in ok:
        for j in ok:
            if i < j and len(ok[i]) == len(ok[j]) and ok[i] @ ok[j] >= cosine:
                n[i] += 1
                n[j] += 1
                up[max(top(i), top(j))] = min(top(i), top(j))
    least = {}
    for i, v in enumerate(rows):
        least[top(i)] = min(least.get(top(i), v[0]), v[0])
    return sorted((v[0], n[i], least[top(i)], v[0] == least[top(i)]) for i, v in enumerate(rows))


def made(seed, n=400, dim=8):
    r = np.random.default_rng(seed)
    x = r.normal(size=(n, dim))
    for i in range(40, n, 3):
        x[i] = x[r.integers(0, i)] + r.normal(size=dim) * r.choice([0.001, 0.05, 0.2, 0.4])
    x[300:340] = x[7] + r.normal(size=(40, dim)) * 0.01
    rows = [(int(i), [float(np.float32(y)) for y in v], 1, "u", 2) for i, v in enumerate(x)]
    rows[50] = (50, rows[51][1], 1, "u", 2)
    rows += [(n, None, 1, "u", 2), (n + 1, [0.0] * dim, 1, "u", 2), (n + 2, [1.0] * (dim - 1) + [float("nan")], 1, "u", 2), (n + 3, [None] + [1.0] * (dim - 1), 1, "u", 2), (n + 4, [], 1, "u", 2), (n + 5, [1.0, 2.0], 1, "u", 2), (n + 6, [2.0, 4.0], 1, "u", 2), (n + 7, rows[60][1], 1, "u", 2)]
    return rows


def test_against_all_pairs(spark):
    rows = made(1)
    df = spark.createDataFrame(rows, SCHEMA).repartition(3)
    for size in (64, 4096):
        got = sorted(map(tuple, C.links(df, rows=size).collect()))
        assert got == brute(rows)


def test_tree_is_nested():
    x = np.random.default_rng(3).normal(size=(500, 3))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    tree = C.CoverTree(x)
    for radius, cut, got in zip((*C.CoverTree.RADII, 0), tree.cuts, tree.radius, strict=True):
        assert (got <= radius + 1e-9).all()
        assert cut[0] == 0 and cut[-1] == 500
    for above, below in zip(tree.cuts[:-1], tree.cuts[1:], strict=True):
        assert set(above) <= set(below)


def test_traversal_from_the_roots_decides_and_prunes():
    """Clusters of clusters of clusters: node pairs are met on every level, most are left out early, and what is found is exact."""
    r = np.random.default_rng(5)
    x = np.zeros((1, 16))
    for scale in (1.0, 0.3, 0.1, 0.03, 0.01):
        x = (x[:, None] + r.normal(size=(len(x), 6, 16)) * scale).reshape(-1, 16)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    a, b = C.CoverTree(x[::2]), C.CoverTree(x[1::2])
    for left, right in ((a, a), (a, b)):
        seen, found = [], np.zeros((len(left.x), len(right.x)), bool)
        for _, i, j, level in C.pairs_of(left, right, 0.9, seen):
            for p, q in zip(i, j, strict=True):
                found[left.cuts[level][p] : left.cuts[level][p + 1], right.cuts[level][q] : right.cuts[level][q + 1]] = True
        if left is right:
            found |= found.T
            np.fill_diagonal(found, True)
        assert (found == (left.x @ right.x.T >= 0.9)).all()
        met = {k: (sum(m for lv, m, _ in seen if lv == k), sum(o for lv, _, o in seen if lv == k)) for k in range(len(left.cuts))}
        between = [k for k in range(1, len(left.cuts) - 1) if met[k][0]]
        assert met[0] == (1, 1) and len(between) >= 3 and sum(m for m, _ in met.values()) < found.size / 4
        assert all(0 < met[k][1] < met[k][0] for k in between[:-1])


def test_null_and_repeated_ids(spark):
    rows = [(None, [1.0, 0.0], 1, "u", 2), (None, [1.0, 0.0], 1, "u", 2), (3, [1.0, 0.01], 1, "u", 2), (3, [1.0, 0.0], 1, "u", 2), (4, [0.0, 1.0], 1, "u", 2)]
    got = sorted(map(tuple, C.links(spark.createDataFrame(rows, SCHEMA)).collect()), key=str)
    assert got == [(3, 1, 3, True), (3, 1, 3, True), (4, 0, 4, True), (None, 0, None, True), (None, 0, None, True)]


def test_nothing_to_link(spark):
    assert C.links(spark.createDataFrame([], SCHEMA)).count() == 0
    assert [tuple(r) for r in C.links(spark.createDataFrame([(1, None, 1, "u", 2)], SCHEMA)).collect()] == [(1, 0, 1, True)]


def test_pairs_of_blocks_shuffle_no_vectors(spark, monkeypatch):
    """Blocks are read where they are stored, however many pairs they make, and components are as wide as they came."""
    keep, plans, tables = C.store, {}, {}

    def noted(df, name):
        plans[name] = df._jdf.queryExecution().toString()
        tables[name] = keep(df, name)
        return tables[name]

    monkeypatch.setattr(C, "store", noted)
    rows = made(2)
    assert sorted(map(tuple, C.links(spark.createDataFrame(rows, SCHEMA), rows=64).collect())) == brute(rows)
    assert tables["blocks"].count() > 4
    assert "Exchange hashpartitioning" not in plans["found"]
    assert {len(r["raw"]) for r in tables["distinct"].collect()} == {4 * 8, 4 * 2}


def test_components_in_double(spark):
    """Double components keep their digits, and their size doesn't matter."""
    x = np.random.default_rng(8).normal(size=6)
    y = np.r_[-x[1], x[0], 0, 0, 0, 0] / np.hypot(x[0], x[1])
    at = [np.cos(a) * x / np.linalg.norm(x) + np.sin(a) * y for a in (0, np.arccos(0.9) - 1e-9, np.arccos(0.9) + 1e-9)]
    rows = [(0, (at[0] * 1e300).tolist()), (1, (at[1] * 1e-300).tolist()), (2, at[2].tolist()), (3, [1e300] * 5 + [float("inf")])]
    got = sorted(map(tuple, C.links(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()))
    assert got == [(0, 1, 0, True), (1, 2, 0, False), (2, 1, 0, False), (3, 0, 3, True)]


def test_tiles_by_some_components_leave_nothing_out():
    """Vectors of many components, with few and with many pairs near the threshold in a tile."""
    r = np.random.default_rng(9)
    x = r.normal(size=(1500, C.WIDE + 8))
    x[:300] = x[0] + r.normal(size=(300, x.shape[1])) * 0.34
    x[300:320] = x[400:420] + r.normal(size=(20, x.shape[1])) * 0.45
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    r.shuffle(x)
    a, b = C.CoverTree(x[:700]), C.CoverTree(x[700:])
    for left, right in ((a, a), (a, b)):
        found = np.zeros((len(left.x), len(right.x)), bool)
        for _, i, j, level in C.pairs_of(left, right, 0.9):
            for p, q in zip(i, j, strict=True):
                found[left.cuts[level][p] : left.cuts[level][p + 1], right.cuts[level][q] : right.cuts[level][q + 1]] = True
        if left is right:
            found |= found.T
            np.fill_diagonal(found, True)
        want = left.x @ right.x.T >= 0.9
        assert want.sum() > len(left.x) and (found == want).all()


def test_levels_that_join_few_vectors_are_passed_over():
    """A level of wide nodes that has most of the vectors as nodes of their own costs more than it leaves out."""
    r = np.random.default_rng(10)
    x = r.normal(size=(400, 64))
    x = np.r_[x, np.repeat(x[:100], 2, axis=0) + r.normal(size=(200, 64)) * 0.6]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    tree, seen = C.CoverTree(x), []
    assert 1.25 < 600 / (len(tree.cuts[1]) - 1) < 2
    list(C.pairs_of(tree, tree, 0.9, seen))
    assert {level for level, _, _ in seen} <= {0, len(tree.cuts) - 1}
