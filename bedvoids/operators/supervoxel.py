"""Homogeneous partitions of a density field by local clustering around a lattice of seeds.

Two engines give the same labels. "array" runs all rounds of a step inside one task, on arrays. "relational"
runs every round as joins over all steps at once and keeps only steps that still change; it has no bound on
the size of a step's grid.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.grid import INDEX, GridSpec
from ..functions.scalar import mixed_distance
from ..sources.shared import store

GAMMA = 0.3
SIZE = (3, 3, 3)
#: Centres that the array engine looks at together.
AT_ONCE = 256


def lattice(grid: GridSpec, size: tuple[int, int, int]) -> tuple[int, int, int]:
    return tuple(ceil(n / s) for n, s in zip(grid.n, size, strict=True))


def block_label(grid: GridSpec, size: tuple[int, int, int]) -> Column:
    """Number of the block of `size` voxels that a voxel lies in."""
    _, kb, kc = lattice(grid, size)
    a, b, c = (F.floor(F.col(i) / s) for i, s in zip(INDEX, size, strict=True))
    return ((a * kb + b) * kc + c).cast("int")


def seeds(field: DataFrame, grid: GridSpec, size: tuple[int, int, int] = SIZE) -> DataFrame:
    """step, cluster, cx, cy, cz, cv: mean position of each block and the density of the voxel nearest to it."""
    blocks = field.select("step", "voxel", *INDEX, "density", block_label(grid, size).alias("cluster"))
    mean = blocks.groupBy("step", "cluster").agg(*[F.avg(i).alias(c) for i, c in zip(INDEX, ("cx", "cy", "cz"), strict=True)])
    both = blocks.join(mean, ["step", "cluster"])
    squares = (F.col("ix") - F.col("cx")) * (F.col("ix") - F.col("cx")) + (F.col("iy") - F.col("cy")) * (F.col("iy") - F.col("cy")) + (F.col("iz") - F.col("cz")) * (F.col("iz") - F.col("cz"))
    return both.groupBy("step", "cluster", "cx", "cy", "cz").agg(F.min_by("density", F.struct(squares.alias("d"), F.col("voxel"))).cast("double").alias("cv"))


def candidates(field: DataFrame, centres: DataFrame, size: tuple[int, int, int], window: str = "closed") -> DataFrame:
    """Voxels with every centre whose window they lie in: an equi-join on cells, and the window test."""
    reach = centres
    for axis, s in zip("xyz", size, strict=True):
        reach = reach.withColumn(f"k{axis}", F.explode(F.sequence(F.floor((F.col(f"c{axis}") - s) / s).cast("int"), F.floor((F.col(f"c{axis}") + s) / s).cast("int"))))
    cells = field.select("step", "voxel", *INDEX, "density", *[F.floor(F.col(i) / s).cast("int").alias(f"k{axis}") for axis, i, s in zip("xyz", INDEX, size, strict=True)])
    test = F.lit(True)
    for axis, i, s in zip("xyz", INDEX, size, strict=True):
        d = F.col(i) - F.col(f"c{axis}")
        test = test & (F.abs(d) <= s if window == "closed" else (d >= -s) & (d < s))
    return cells.join(reach, ["step", "kx", "ky", "kz"]).where(test)


def assign(field: DataFrame, centres: DataFrame, size: tuple[int, int, int] = SIZE, gamma: float = GAMMA, window: str = "closed") -> DataFrame:
    """step, voxel, cluster, n_candidates: the nearest centre in reach of each voxel; ties go to the lowest number."""
    near = candidates(field, centres, size, window)
    d = mixed_distance([(F.col(i), F.col(c)) for i, c in zip(INDEX, ("cx", "cy", "cz"), strict=True)], (F.col("density"), F.col("cv")), gamma)
    return near.groupBy("step", "voxel").agg(F.min_by("cluster", F.struct(d.alias("d"), F.col("cluster"))).alias("cluster"), F.count(F.lit(1)).alias("n_candidates"))


def update(labels: DataFrame, field: DataFrame) -> DataFrame:
    """step, cluster, cx, cy, cz, cv: mean position and density of the members."""
    both = labels.select("step", "voxel", "cluster").join(field, ["step", "voxel"])
    return both.groupBy("step", "cluster").agg(*[F.avg(i).alias(c) for i, c in zip(INDEX, ("cx", "cy", "cz"), strict=True)], F.avg("density").alias("cv"))


def slic(field: DataFrame, grid: GridSpec, size: tuple[int, int, int] = SIZE, gamma: float = GAMMA, max_iter: int = 20, engine: str = "array", window: str = "closed") -> tuple[DataFrame, DataFrame, DataFrame]:
    """labels (step, voxel, cluster), centres (step, cluster, cx, cy, cz, cv, size), report (step, iteration, changed, distances, converged).

    A voxel out of reach of every centre keeps its label (at first its block); a cluster without members keeps its centre.
    """
    if engine == "array":
        return _array(field, grid, size, gamma, max_iter, window)
    if engine == "relational":
        return _relational(field, grid, size, gamma, max_iter, window)
    raise ValueError(engine)


def _relational(field, grid, size, gamma, max_iter, window):
    field = store(field.select("step", "voxel", *INDEX, "density"), "field")
    labels = store(field.select("step", "voxel", block_label(grid, size).alias("cluster")), "labels")
    centres = store(seeds(field, grid, size), "centres")
    done_labels, done_centres, reports = [], [], []
    for i in range(1, max_iter + 1):
        new = assign(field, centres, size, gamma, window).withColumnRenamed("cluster", "to")
        both = labels.join(new, ["step", "voxel"], "left").select("step", "voxel", F.coalesce("to", "cluster").alias("cluster"), (F.coalesce("to", "cluster") != F.col("cluster")).alias("moved"), F.coalesce("n_candidates", F.lit(0)).alias("n_candidates"))
        both = store(both, "labels")
        report = store(both.groupBy("step").agg(F.count_if("moved").alias("changed"), F.sum("n_candidates").alias("distances")).select("step", F.lit(i).alias("iteration"), "changed", "distances", (F.col("changed") == 0).alias("converged")), "report")
        reports.append(report)
        means = update(both, field).select("step", "cluster", *[F.col(c).alias(f"m{c}") for c in ("cx", "cy", "cz", "cv")])
        centres = store(centres.join(means, ["step", "cluster"], "left").select("step", "cluster", *[F.coalesce(f"m{c}", c).alias(c) for c in ("cx", "cy", "cz", "cv")]), "centres")
        still = report.where("not converged").select("step")
        ended = report.where("converged").select("step")
        last = i == max_iter
        done_labels.append(both.select("step", "voxel", "cluster") if last else both.join(ended, "step", "left_semi").select("step", "voxel", "cluster"))
        done_centres.append(centres if last else centres.join(ended, "step", "left_semi"))
        if last or still.isEmpty():
            break
        labels, centres, field = (x.join(still, "step", "left_semi") for x in (both.select("step", "voxel", "cluster"), centres, field))
    union = lambda parts: _union(parts)
    labels, centres = union(done_labels), union(done_centres)
    sizes = labels.groupBy("step", "cluster").agg(F.count(F.lit(1)).alias("size"))
    centres = centres.join(sizes, ["step", "cluster"], "left").withColumn("size", F.coalesce("size", F.lit(0)))
    return labels, centres, union(reports)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def cluster_arrays(density: np.ndarray, size: tuple[int, int, int], gamma: float, max_iter: int, window: str = "closed") -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """Labels, centres (rows cx, cy, cz, cv) and (changed, distances) of each round for one dense field."""
    n = density.shape
    flat = density.reshape(-1).astype(float)
    pos = np.stack(np.unravel_index(np.arange(flat.size), n), 1).astype(float)
    size = tuple(size)
    k = tuple(ceil(a / s) for a, s in zip(n, size, strict=True))
    label = np.ravel_multi_index(tuple((pos[:, i] // size[i]).astype(int) for i in range(3)), k)
    total = k[0] * k[1] * k[2]

    def means(values: np.ndarray, count: np.ndarray) -> np.ndarray:
        return np.bincount(label, values, minlength=total) / np.maximum(count, 1)

    count = np.bincount(label, minlength=total)
    centre = np.stack([means(pos[:, i], count) for i in range(3)] + [np.zeros(total)], 1)
    d = ((pos - centre[label, :3]) ** 2) @ np.ones(3)
    order = np.lexsort((np.arange(flat.size), d, label))
    first = np.r_[True, label[order][1:] != label[order][:-1]]
    centre[label[order][first], 3] = flat[order][first]
    report = []
    wide = [2 * x + 1 for x in size]
    for _ in range(max_iter):
        best, to, tested = np.full(flat.size, np.inf), np.full(flat.size, total, np.int32), 0
        corner = np.ceil(centre[:, :3] - size).astype(np.int32)
        # squared gaps and validity of every place of a window, axis by axis
        at = [corner[:, i, None] + np.arange(wide[i], dtype=np.int32) for i in range(3)]
        gap = [at[i] - centre[:, i, None] for i in range(3)]
        ok = [(at[i] >= 0) & (at[i] < n[i]) & ((np.abs(gap[i]) <= size[i]) if window == "closed" else (gap[i] >= -size[i]) & (gap[i] < size[i])) for i in range(3)]
        for c in range(0, total, AT_ONCE):  # so few that what they are compared with stays near the processor
            (ax, ay, az), (gx, gy, gz), (ox, oy, oz) = ([x[c : c + AT_ONCE] for x in rows] for rows in (at, gap, ok))
            inside = np.flatnonzero((ox[:, :, None] & oy[:, None, :])[..., None] & oz[:, None, None, :])
            plane, z = inside // wide[2], inside % wide[2]
            own = plane // (wide[0] * wide[1])
            place = (ax[:, :, None] * n[1] + ay[:, None, :]).ravel()[plane] * n[2] + az.ravel()[own * wide[2] + z]
            square = ((gx * gx)[:, :, None] + (gy * gy)[:, None, :]).ravel()[plane] + (gz * gz).ravel()[own * wide[2] + z]
            tested += len(own)
            d = gamma * np.sqrt(square) + (1 - gamma) * np.abs(flat[place] - centre[c : c + AT_ONCE, 3][own])
            # centres come in order of their numbers: an equal distance doesn't take a voxel from an earlier one
            near = np.flatnonzero(d < best[place])
            place, d, own = place[near], d[near], own[near]
            np.minimum.at(best, place, d)
            first = np.flatnonzero(best[place] == d)
            place, own = place[first], (own[first] + c).astype(np.int32)
            to[place] = total
            np.minimum.at(to, place, own)
        new = np.where(to < total, to, label)
        changed = int((new != label).sum())
        label = new
        report.append((changed, tested))
        count = np.bincount(label, minlength=total)
        fresh = np.stack([means(pos[:, i], count) for i in range(3)] + [means(flat, count)], 1)
        centre = np.where((count > 0)[:, None], fresh, centre)
        if not changed:
            break
    return label, centre, report


def structs(**columns: np.ndarray | pa.Array) -> pa.ListArray:
    """One list of structs from arrays of one length."""
    rows = pa.StructArray.from_arrays([pa.array(v) for v in columns.values()], names=list(columns))
    return pa.ListArray.from_arrays(pa.array([0, len(rows)], pa.int32()), rows)


CENTRES = "array<struct<cluster:int,cx:double,cy:double,cz:double,cv:double,size:bigint>>"
REPORT = "array<struct<iteration:int,changed:bigint,distances:bigint,converged:boolean>>"


def centre_rows(label: np.ndarray, centre: np.ndarray) -> pa.ListArray:
    return structs(cluster=np.arange(len(centre), dtype=np.int32), **{c: np.ascontiguousarray(centre[:, i]) for i, c in enumerate(("cx", "cy", "cz", "cv"))}, size=np.bincount(label, minlength=len(centre)))


def report_rows(report: list[tuple[int, int]]) -> pa.ListArray:
    changed, distances = (np.array(x, np.int64) for x in zip(*report, strict=True))
    return structs(iteration=np.arange(1, len(report) + 1, dtype=np.int32), changed=changed, distances=distances, converged=changed == 0)


def _array(field, grid, size, gamma, max_iter, window):
    n = grid.n

    def run(table: pa.Table) -> pa.Table:
        step = table.column("step")[0].as_py()
        density = np.zeros(grid.voxels)
        density[table.column("voxel").to_numpy()] = table.column("density").to_numpy()
        label, centre, report = cluster_arrays(density.reshape(n), size, gamma, max_iter, window)
        labels = pa.ListArray.from_arrays(pa.array([0, len(label)], pa.int32()), pa.array(label.astype(np.int32)))
        return pa.table({"step": pa.array([step], pa.int32()), "labels": labels, "centres": centre_rows(label, centre), "report": report_rows(report)})

    schema = f"step int, labels array<int>, centres {CENTRES}, report {REPORT}"
    packed = store(field.select(F.col("step").cast("int").alias("step"), "voxel", "density").groupBy("step").applyInArrow(run, schema), "slic")
    labels = packed.select("step", F.posexplode("labels").alias("voxel", "cluster")).withColumn("voxel", F.col("voxel").cast("long"))
    return labels, packed.select("step", F.inline("centres")), packed.select("step", F.inline("report"))


def neighbours_python() -> type:
    """A table function of (ix, iy, iz, connectivity): the neighbours of a voxel; for small inputs."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="nx int, ny int, nz int")
    class Neighbours:
        def eval(self, ix: int, iy: int, iz: int, connectivity: int) -> Iterator[tuple[int, int, int]]:
            most = {6: 1, 18: 2, 26: 3}[connectivity]
            for a in (-1, 0, 1):
                for b in (-1, 0, 1):
                    for c in (-1, 0, 1):
                        if 0 < abs(a) + abs(b) + abs(c) <= most:
                            yield ix + a, iy + b, iz + c

    return Neighbours
