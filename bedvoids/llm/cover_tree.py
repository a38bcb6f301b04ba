"""Near-duplicate vectors: exact threshold pairs by dual traversal of cover trees.

Vectors are scaled to length 1; cosine c means distance sqrt(2 - 2c). They are dealt into cells around
pivots and cells into blocks of at most `rows` vectors. A block's cover tree has nested levels with
halving radii: each node's centre is one of its vectors, all vectors of a node lie within its radius, and
the first child keeps the parent's centre. Pairs of blocks, then pairs of nodes from the roots down level by
level, are left out when their centres are farther apart than the threshold and both covering radii allow, and
taken as a whole when even their farthest vectors are near enough; the rest is decided by the cosine in double.
A descent passes over levels that split hardly any node more, as deeper ones bound better at the same cost. Children
of nodes with many of them are bounded by tiles of products of their centres.

Blocks are stored once, with components as wide as they came, and scaled to length 1 in double where they are read.
Pairs of blocks are made by a join without keys, which reads the stored table again and shuffles nothing: what lies
on disk grows with the number of vectors, not with that of the pairs.

Equal vectors are compared once and count as often as they stand. Null and zero vectors, and those with
null or non-finite components, link with nothing; so do vectors of another length (only vectors of equal
length are compared). Repeated ids are rows of their own; null ids link with nothing. Extra columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H
from .store import components, store

ROWS = 16384
#: Pairs of children of one node pair from which on products are taken in tiles, and node pairs looked at at once.
MANY, AT_ONCE, TILE = 1 << 14, 1 << 15, 512
#: From so many components on, tiles begin with half of them; with more than this share left open, all of them are taken at once.
WIDE, MOST = 32, 1 / 64
#: A level is passed over if one below it has no more than so many times its nodes.
HARDLY = 4.0


def usable(kind: str):
    """vec_id, bytes of the vector's components as numbers of `kind` (NumPy's name); null where the vector can't be compared."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column("embedding")
            size = pc.fill_null(pc.list_value_length(column), 0).to_numpy()
            y = column.flatten().to_numpy(zero_copy_only=False).astype(kind, copy=False)  # null components are NaN
            row = np.repeat(np.arange(len(size)), size)
            ok = (np.bincount(row[~np.isfinite(y)], minlength=len(size)) == 0) & (np.bincount(row[y != 0], minlength=len(size)) > 0)
            ends = np.cumsum(np.where(ok, size, 0)) * y.itemsize
            data = np.ascontiguousarray(y[ok[row]])
            unit = pa.Array.from_buffers(pa.large_binary(), len(size), [pa.py_buffer(np.packbits(ok, bitorder="little")), pa.py_buffer(np.r_[0, ends].astype(np.int64)), pa.py_buffer(data)])
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), unit.cast(pa.binary())], names=["vec_id", "raw"])

    return run


def _units(raw: bytes | pa.Buffer, n: int, kind: str) -> np.ndarray:
    """Rows of length 1, in double."""
    x = np.frombuffer(raw, kind).reshape(n, -1).astype(float)
    x /= np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


class CoverTree:
    """Nested levels over unit vectors: for each level the centre and radius of its nodes, and the children's range."""

    RADII = (2.0, 1.0, 0.5, 0.25, 0.125, 0.0625)

    def __init__(self, x: np.ndarray):
        n = len(x)
        order = np.arange(n)
        level_of = np.zeros(n, np.int64)  # node of each vector at the present level
        cuts = [np.array([0, n])] if n else [np.array([0])]
        for radius in self.RADII[1:]:
            owner = np.empty(n, np.int64)  # centre (a row of x[order]) of each vector
            for a, b in zip(cuts[-1][:-1], cuts[-1][1:], strict=True):
                owner[a:b] = a if b - a == 1 else a + _net(x[order[a:b]], radius)
            # children stand together, the parent's centre and its own first
            by = np.lexsort((owner != np.arange(n), owner, level_of))
            order, owner = order[by], owner[by]
            new = np.r_[True, owner[1:] != owner[:-1]]
            level_of = np.cumsum(new) - 1
            cuts.append(np.r_[np.flatnonzero(new), n])
        self.order, self.x = order, x[order]
        # leaves: the vectors themselves
        self.cuts = [*cuts, np.arange(n + 1)]
        self.radius = [self._radii(c) for c in self.cuts]

    def parts(self) -> bytes:
        return pickle.dumps((self.cuts, self.radius))

    @classmethod
    def of_parts(cls, x: np.ndarray, parts: bytes) -> CoverTree:
        """The tree over vectors that stand in its order already."""
        tree = cls.__new__(cls)
        tree.order, tree.x = np.arange(len(x)), x
        tree.cuts, tree.radius = pickle.loads(parts)
        return tree

    def _radii(self, cut: np.ndarray) -> np.ndarray:
        if len(cut) < 2:
            return np.zeros(0)
        size = np.diff(cut)
        d = np.zeros(cut[-1])
        many = np.flatnonzero(np.repeat(size > 1, size))
        if len(many):
            d[many] = np.linalg.norm(self.x[many] - self.x[np.repeat(cut[:-1], size)[many]], axis=1)
        return np.maximum.reduceat(d, cut[:-1])


def _net(x: np.ndarray, radius: float) -> np.ndarray:
    """For each row the centre it is given to; centres are rows, the first is row 0, and none lies within `radius` of an earlier one."""
    near = 1 - radius * radius / 2  # as a cosine
    centres = np.zeros(0, np.int64)
    owner = np.empty(len(x), np.int64)
    for i in range(0, len(x), 256):
        part = x[i : i + 256]
        free = np.ones(len(part), bool)
        if len(centres):
            c = part @ x[centres].T
            best = c.argmax(1)
            hit = c[np.arange(len(part)), best] >= near
            owner[i : i + 256][hit] = centres[best[hit]]
            free = ~hit
        at = np.flatnonzero(free)
        close = part[at] @ part[at].T >= near
        mine = np.full(len(at), -1)
        for k in range(len(at)):
            if mine[k] < 0:
                mine[(mine < 0) & close[k]] = k
                mine[k] = k
        owner[i + at] = i + at[mine]
        centres = np.r_[centres, i + at[np.unique(mine)]] if len(at) else centres
    return owner


def pairs_of(a: CoverTree, b: CoverTree, cosine: float, seen: list[tuple[int, int, int]] | None = None) -> Iterator[tuple[str, np.ndarray, np.ndarray, int]]:
    """Node pairs within the threshold: ("all", nodes of a, nodes of b, level) or ("one", vectors of a, vectors of b, level).

    `seen` gets (level, node pairs met, node pairs left open) along the way.
    """
    limit = np.sqrt(max(0.0, 2 - 2 * cosine))
    last, own = len(a.cuts) - 1, a is b
    size = [[len(c) - 1 for c in t.cuts] for t in (a, b)]
    down = [max(k for k in range(level + 1, last + 1) if all(n[k] <= HARDLY * n[level + 1] for n in size)) for level in range(last)]
    # what a node pair opens is looked at before the next one: no more than a stretch for each level is held
    stack = [iter([(0, np.zeros(1, np.int64), np.zeros(1, np.int64))])]
    while stack:
        top = next(stack[-1], None)
        if top is None:
            stack.pop()
            continue
        level, i, j = top
        met = len(i)
        cos = np.einsum("ij,ij->i", a.x[a.cuts[level][i]], b.x[b.cuts[level][j]])
        if level == last:
            hit = (cos >= cosine) & ((i < j) if own else True)
            if seen is not None:
                seen.append((level, met, 0))
            if hit.any():
                yield "one", i[hit], j[hit], level
            continue
        if own:  # a vector isn't its own partner
            more = (i != j) | (a.cuts[level][i + 1] - a.cuts[level][i] > 1)
            i, j, cos = i[more], j[more], cos[more]
        d = np.sqrt(np.maximum(0.0, 2 - 2 * cos))
        ra, rb = a.radius[level][i], b.radius[level][j]
        whole = d + ra + rb <= limit - 1e-6
        if whole.any():
            yield "all", i[whole], j[whole], level
        open_ = ~whole & (d <= limit + ra + rb + 1e-6)
        if seen is not None:
            seen.append((level, met, int(open_.sum())))
        if open_.any():
            stack.append(_opened(a, b, level, down[level], i[open_], j[open_], limit))


def _opened(a: CoverTree, b: CoverTree, level: int, below: int, i: np.ndarray, j: np.ndarray, limit: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """The pairs of descendants on the level `below` of node pairs, without those that mirror each other."""
    own = a is b
    fa, ta = (np.searchsorted(a.cuts[below], a.cuts[level][i + s]) for s in (0, 1))
    fb, tb = (np.searchsorted(b.cuts[below], b.cuts[level][j + s]) for s in (0, 1))
    size = (ta - fa) * (tb - fb)
    few = np.flatnonzero(size < MANY)
    for s in _runs(size[few], AT_ONCE):
        k = few[s]
        at = np.repeat(k, size[k])
        within = np.arange(len(at)) - np.repeat(np.cumsum(size[k]) - size[k], size[k])
        wide = (tb - fb)[at]
        x, y = fa[at] + within // wide, fb[at] + within % wide
        if own:
            keep = (i[at] != j[at]) | (x <= y)
            x, y = x[keep], y[keep]
        yield below, x, y
    for k in np.flatnonzero(size >= MANY):
        for x, y in _tiles(a, b, below, np.arange(fa[k], ta[k]), np.arange(fb[k], tb[k]), limit, own and i[k] == j[k]):
            for c in range(0, len(x), AT_ONCE):
                yield below, x[c : c + AT_ONCE], y[c : c + AT_ONCE]


def _tiles(a: CoverTree, b: CoverTree, level: int, na: np.ndarray, nb: np.ndarray, limit: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Of all pairs of nodes of one level: those that their radii don't rule out, with room for single precision."""
    # nodes in order of radius: most tiles are of single vectors, which have one bound
    na, nb = na[np.argsort(a.radius[level][na], kind="stable")], nb[np.argsort(b.radius[level][nb], kind="stable")]
    xa, xb = (t.x[t.cuts[level][k]].astype(np.float32) for t, k in ((a, na), (b, nb)))
    room = 1e-5 + 2e-7 * xa.shape[1]
    # a product is no greater than that of some components and of the lengths of what is left, which takes fewer steps
    some = xa.shape[1] // 2 if xa.shape[1] >= WIDE else xa.shape[1]
    ca, cb = (np.c_[x[:, :some], np.linalg.norm(x[:, some:], axis=1)] for x in (xa, xb))
    space, flags = np.empty(TILE * TILE, np.float32), np.empty(TILE * TILE, bool)
    for i in range(0, len(na), TILE):
        ia = na[i : i + TILE]
        ra = a.radius[level][ia]
        for j in range(i if same else 0, len(nb), TILE):
            ib = nb[j : j + TILE]
            rb = b.radius[level][ib]
            reach = limit + (ra[-1] + rb[-1] if ra[0] == ra[-1] and rb[0] == rb[-1] else ra[:, None] + rb)
            least = (1 - np.minimum(reach, 2.0) ** 2 / 2 - room).astype(np.float32)
            shape = len(ia), len(ib)
            cos, near = (s[: shape[0] * shape[1]].reshape(shape) for s in (space, flags))
            open_ = np.flatnonzero(np.greater_equal(np.matmul(ca[i : i + TILE], cb[j : j + TILE].T, out=cos), least, out=near))
            if len(open_) > MOST * cos.size:
                open_ = np.flatnonzero(np.greater_equal(np.matmul(xa[i : i + TILE], xb[j : j + TILE].T, out=cos), least, out=near))
            p, q = np.divmod(open_, len(ib))
            if 0 < len(open_) <= MOST * cos.size:
                keep = np.einsum("ij,ij->i", xa[i + p], xb[j + q]) >= (least if least.ndim == 0 else least[p, q])
                p, q = p[keep], q[keep]
            p, q = ia[p], ib[q]
            if same:  # each pair once, in the order of the tree
                if i == j:
                    keep = p <= q
                    p, q = p[keep], q[keep]
                else:
                    p, q = np.minimum(p, q), np.maximum(p, q)
            if len(p):
                yield p, q


def _runs(size: np.ndarray, most: int) -> Iterator[slice]:
    i = 0
    ends = np.cumsum(size)
    while i < len(size):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + most, "right")))
        yield slice(i, j)
        i = j


class _Forest:
    """Union-find: keeps links only where they join two groups."""

    def __init__(self, n: int):
        self.up = list(range(n))
        self.edges: list[tuple[int, int]] = []

    def top(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> None:
        p, q = self.top(i), self.top(j)
        if p != q:
            self.up[max(p, q)] = min(p, q)
            self.edges.append((i, j))


class Block(NamedTuple):
    """A tree with the ids of its vectors and how often each stands, in the tree's order."""

    tree: CoverTree
    ids: np.ndarray
    m: np.ndarray

    @classmethod
    def of(cls, x: np.ndarray, ids: np.ndarray, m: np.ndarray) -> Block:
        tree = CoverTree(x)
        return cls(tree, ids[tree.order], m[tree.order])


def block_links(left: Block, right: Block, cosine: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """a, b, links: how many vectors each vector links with, as rows (id, id, count), and links that hold the groups together (id, id, 0)."""
    own = left is right
    (a, ids_a, m_a), (b, ids_b, m_b) = left, right
    na = len(ids_a)
    count_a, count_b = np.zeros(na, np.int64), np.zeros(len(ids_b), np.int64)
    at_b = 0 if own else na
    forest = _Forest(na + (0 if own else len(ids_b)))
    sum_a, sum_b = np.r_[0, np.cumsum(m_a)], np.r_[0, np.cumsum(m_b)]
    for kind, i, j, level in pairs_of(a, b, cosine):
        if kind == "one":
            np.add.at(count_a, i, m_b[j])
            np.add.at(count_a if own else count_b, j, m_a[i])
            for p, q in zip(i.tolist(), (j + at_b).tolist(), strict=True):
                forest.join(p, q)
            continue
        for p, q in zip(i.tolist(), j.tolist(), strict=True):
            fa, ta, fb, tb = *a.cuts[level][p : p + 2].tolist(), *b.cuts[level][q : q + 2].tolist()
            if own and p == q:
                count_a[fa:ta] += sum_a[ta] - sum_a[fa] - m_a[fa:ta]
            else:
                count_a[fa:ta] += sum_b[tb] - sum_b[fb]
                (count_a if own else count_b)[fb:tb] += sum_a[ta] - sum_a[fa]
            for k in range(fa + 1, ta):
                forest.join(fa, k)
            for k in range(fb, tb):
                forest.join(fa, k + at_b)
    both = ids_a if own else np.r_[ids_a, ids_b]
    total = count_a if own else np.r_[count_a, count_b]
    there = np.flatnonzero(total)
    edges = np.array(forest.edges, np.int64).reshape(-1, 2)
    return np.r_[both[there], both[edges[:, 0]]], np.r_[both[there], both[edges[:, 1]]], np.r_[total[there], np.zeros(len(edges), np.int64)]


def _pack(kind: str):
    """The rows of a block as one row, with their tree."""

    def run(table: pa.Table) -> pa.Table:
        raw = table.column("raw").to_pylist()
        ids, m = (table.column(c).to_numpy().astype(np.int64) for c in ("rep", "m"))
        tree, ids, m = Block.of(_units(b"".join(raw), len(raw), kind), ids, m)
        packed = (ids.tobytes(), m.tobytes(), b"".join([raw[k] for k in tree.order]), tree.parts())
        cells = {"block": table.column("block").slice(0, 1), **{c: pa.array([v], pa.binary()) for c, v in zip(("ids", "m", "raw", "tree"), packed, strict=True)}}
        return pa.table(cells | {"centre": pa.array([tree.x[0].tolist()], pa.list_(pa.float64())), "radius": pa.array([float(tree.radius[0][0])])})

    return run


def _solve(cosine: float, kind: str):
    """Links of each pair of blocks, which stand side by side in a row."""

    def load(batch: pa.RecordBatch, k: int, side: str) -> Block:
        ids, m, raw, tree = (batch.column(f"{c}_{side}")[k].as_buffer() for c in ("ids", "m", "raw", "tree"))
        ids = np.frombuffer(ids, np.int64)
        return Block(CoverTree.of_parts(_units(raw, len(ids), kind), tree), ids, np.frombuffer(m, np.int64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, left = None, None
            for k, (p, q) in enumerate(zip(batch.column("block_l").to_pylist(), batch.column("block_r").to_pylist(), strict=True)):
                if p != at:
                    at, left = p, load(batch, k, "l")
                a, b, n = block_links(left, left if p == q else load(batch, k, "r"), cosine)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(n)], names=["a", "b", "links"])

    return run


def _cells(pivots: np.ndarray, kind: str, first: np.ndarray | None = None):
    """The cell of each vector or, with the number of the first block of each cell, its block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw = batch.column("raw").to_pylist()
            x = _units(b"".join(raw), len(raw), kind) if raw else np.zeros((0, pivots.shape[1]))
            cell = (x @ pivots.T).argmax(1)
            if first is None:
                yield pa.RecordBatch.from_arrays([pa.array(cell)], names=["cell"])
                continue
            part = H.mix(batch.column("rep").to_numpy().astype(H.U)) % (first[cell + 1] - first[cell]).astype(H.U)
            yield pa.RecordBatch.from_arrays([pa.array(first[cell] + part.astype(np.int64)), *batch.columns], names=["block", *batch.schema.names])

    return run


def links(vectors: DataFrame, cosine: float = 0.9, rows: int = ROWS) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of (vec_id, embedding)."""
    single = vectors.schema["embedding"].dataType.elementType.typeName() == "float"
    kind, wide = ("<f4", "array<float>") if single else ("<f8", "array<double>")
    read = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast(wide).alias("embedding")).mapInArrow(usable(kind), "vec_id long, raw binary")
    # rows find their vector by a digest, so the vectors themselves are shuffled to be made distinct and to be put in blocks only
    key = F.unhex(F.sha2("raw", 256)).alias("key")
    all_ = store(read.select("vec_id", key), "vectors")
    one = read.where("raw is not null and vec_id is not null").groupBy("raw").agg(F.min("vec_id").alias("head"), F.count(F.lit(1)).alias("m"))
    one = store(one.select("raw", key, "head", "m", F.octet_length("raw").alias("dim"), F.monotonically_increasing_id().alias("rep")), "distinct")
    # a pivot for about `rows` vectors, 256 at most; which ones is a matter of speed only
    sizes = {r["dim"]: r["n"] for r in one.groupBy("dim").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        return all_.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    pieces, blocks = [], 0
    for dim, n in sizes.items():
        like = one.where(F.col("dim") == dim).select("rep", "m", "raw")
        k = min(256, -(-n // rows))
        pivots = np.concatenate([_units(r["raw"], 1, kind) for r in like.orderBy(F.xxhash64("raw"), "raw").limit(k).collect()])
        cells = {0: n} if k == 1 else {r["cell"]: r["n"] for r in like.mapInArrow(_cells(pivots, kind), "cell long").groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}
        first = blocks + np.cumsum([0, *(-(-cells.get(c, 0) // max(1, rows // 2)) for c in range(k))])
        blocks = int(first[-1])
        pieces.append(like.mapInArrow(_cells(pivots, kind, first), "block long, rep long, m long, raw binary"))
    dealt = pieces[0]
    for x in pieces[1:]:
        dealt = dealt.unionByName(x)
    packed = dealt.groupBy("block").applyInArrow(_pack(kind), "block long, ids binary, m binary, raw binary, tree binary, centre array<double>, radius double")
    return _joined(all_, one, store(packed, "blocks"), cosine, kind)


def _joined(all_: DataFrame, one: DataFrame, packed: DataFrame, cosine: float, kind: str) -> DataFrame:
    limit = float(np.sqrt(max(0.0, 2 - 2 * cosine)))
    left, right = (packed.select(*(F.col(c).alias(f"{c}_{side}") for c in packed.columns)) for side in "lr")
    apart = F.sqrt(F.aggregate(F.zip_with("centre_l", "centre_r", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    # no key is equal on both sides, so the stored blocks are read by each task that needs them
    near = (F.col("block_l") <= F.col("block_r")) & F.when(F.size("centre_l") == F.size("centre_r"), apart <= limit + F.col("radius_l") + F.col("radius_r") + 1e-6).otherwise(False)
    sides = left.crossJoin(right).where(near).select(*(f"{c}_{side}" for side in "lr" for c in ("block", "ids", "m", "raw", "tree")))
    found = store(sides.mapInArrow(_solve(cosine, kind), "a long, b long, links long"), "found")
    count = found.where("links > 0").groupBy(F.col("a").alias("rep")).agg(F.sum("links").alias("links"))
    groups = components(found.where("links = 0").select("a", "b")).select(F.col("node").alias("rep"), "component")
    reps = one.select("key", "head", "m", "rep").join(count, "rep", "left").join(groups, "rep", "left").select("key", "m", "head", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "rep").alias("c"))
    least = reps.groupBy("c").agg(F.min("head").alias("component"))
    reps = reps.join(least, "c").select("key", "m", "links", "component")
    rows = all_.join(reps, "key", "left")
    there = F.col("vec_id").isNotNull()
    n_links = F.coalesce(F.when(there, F.col("links") + F.col("m") - 1), F.lit(0)).cast("long")
    component = F.when(there, F.coalesce("component", "vec_id"))
    return rows.select("vec_id", n_links.alias("n_links"), component.alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


#: All pairs of vectors, and what each vector reaches; at cosine 0.9.
SQL = """
WITH RECURSIVE v AS MATERIALIZED (
  SELECT CAST(vec_id AS BIGINT) AS vec_id, list_transform(embedding, lambda y: CAST(y AS DOUBLE)) AS x FROM embeddings
), good AS MATERIALIZED (
  SELECT vec_id, x, sqrt(list_inner_product(x, x)) AS size FROM v WHERE len(x) > 0 AND len(list_filter(x, lambda y: y IS NULL OR NOT isfinite(y))) = 0 AND list_inner_product(x, x) > 0
), links AS MATERIALIZED (
  SELECT a.vec_id AS p, b.vec_id AS q FROM good a JOIN good b ON a.vec_id < b.vec_id AND len(a.x) = len(b.x) WHERE list_inner_product(a.x, b.x) / (a.size * b.size) >= CAST('0.9' AS DOUBLE)
), sides AS MATERIALIZED (SELECT p, q FROM links UNION ALL SELECT q, p FROM links
), reach(vec_id, least_id) USING KEY (vec_id) AS (
  SELECT vec_id, vec_id FROM v
  UNION
  SELECT c.vec_id, min(x.least_id) FROM reach x JOIN sides ON sides.p = x.vec_id JOIN recurring.reach c ON c.vec_id = sides.q WHERE x.least_id < c.least_id GROUP BY c.vec_id
)
SELECT v.vec_id, coalesce(n, 0) AS n_links, least_id AS component_id, least_id = v.vec_id AS kept FROM v JOIN reach USING (vec_id) LEFT JOIN (SELECT p AS vec_id, count(*) AS n FROM sides GROUP BY p) USING (vec_id)
"""
