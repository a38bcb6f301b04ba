"""Connected components of segmented voxels, step by step.

"local" labels a step in one task; "tiled" labels tiles and joins them over their borders, for steps that
don't fit a task; "propagate" finds components of the graph of touching voxels. All give the same numbers:
components of a step are numbered from 1 by their smallest voxel.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.grid import GridSpec
from .graph import components

_MOST = {6: 1, 18: 2, 26: 3}


def half_offsets(connectivity: int) -> list[tuple[int, int, int]]:
    """One of each pair of opposite neighbours."""
    most = _MOST[connectivity]
    return [(a, b, c) for a in (0, 1) for b in (-1, 0, 1) for c in (-1, 0, 1) if (a, b, c) > (0, 0, 0) and abs(a) + abs(b) + abs(c) <= most]


def label_voxels(voxel: np.ndarray, n: tuple[int, int, int], connectivity: int) -> np.ndarray:
    """The smallest voxel of each voxel's component, by union-find over touching pairs."""
    order = np.argsort(voxel)
    v = voxel[order]
    x, y, z = np.unravel_index(v, n)
    up = np.arange(len(v))

    def top(i: int) -> int:
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for a, b, c in half_offsets(connectivity):
        p, q, r = x + a, y + b, z + c
        ok = (p < n[0]) & (q >= 0) & (q < n[1]) & (r >= 0) & (r < n[2])
        to = (p[ok] * n[1] + q[ok]) * n[2] + r[ok]
        at = np.searchsorted(v, to)
        hit = (at < len(v)) & (v[np.minimum(at, len(v) - 1)] == to)
        for i, j in zip(np.flatnonzero(ok)[hit].tolist(), at[hit].tolist(), strict=True):
            i, j = top(i), top(j)
            if i != j:
                up[max(i, j)] = min(i, j)
    out = np.empty(len(v), np.int64)
    out[order] = v[[top(i) for i in range(len(v))]]
    return out


def _touching(at: DataFrame, connectivity: int) -> DataFrame:
    """Pairs (a, b) of node numbers of touching voxels of (step, ix, iy, iz, node)."""
    offsets = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c")) for a, b, c in half_offsets(connectivity)])
    to = at.select("step", F.col("node").alias("a"), "ix", "iy", "iz", F.explode(offsets).alias("o"))
    to = to.select("step", "a", *[(F.col(i) + F.col(f"o.{o}")).alias(i) for i, o in zip(("ix", "iy", "iz"), "abc", strict=True)])
    return to.join(at.select("step", "ix", "iy", "iz", F.col("node").alias("b")), ["step", "ix", "iy", "iz"]).select("a", "b")


def numbered(roots: DataFrame) -> DataFrame:
    """step, voxel, root -> step, voxel, bubble."""
    ids = roots.select("step", "root").distinct().withColumn("bubble", F.row_number().over(Window.partitionBy("step").orderBy("root")))
    return roots.join(ids, ["step", "root"]).select("step", "voxel", "bubble")


def label(voxels: DataFrame, grid: GridSpec, connectivity: int = 6, engine: str = "local", tile: tuple[int, int, int] = (8, 8, 8)) -> DataFrame:
    """step, voxel, ix, iy, iz, bubble from (step, voxel)."""
    at = voxels.select("step", "voxel").distinct()
    if engine == "local":
        roots = at.groupBy("step").applyInArrow(_local(grid.n, connectivity, ["step"]), "step int, voxel long, root long")
    elif engine == "propagate":
        nodes = at.select("step", "voxel", *[c.alias(k) for k, c in grid.indices().items()], _node(grid).alias("node"))
        found = components(_touching(nodes, connectivity))
        roots = nodes.join(found, "node", "left").select("step", "voxel", F.pmod(F.coalesce("component", "node"), F.lit(grid.voxels)).alias("root"))
    elif engine == "tiled":
        cut = at.select("step", "voxel", *[c.alias(k) for k, c in grid.indices().items()])
        cut = cut.withColumn("tile", F.concat_ws(",", *[F.floor(F.col(i) / t).cast("int") for i, t in zip(("ix", "iy", "iz"), tile, strict=True)]))
        own = cut.select("step", "voxel", "tile").groupBy("step", "tile").applyInArrow(_local(grid.n, connectivity, ["step", "tile"]), "step int, tile string, voxel long, root long")
        own = own.select("step", "voxel", "tile", *[c.alias(k) for k, c in grid.indices().items()], (F.col("step") * F.lit(grid.voxels) + F.col("root")).alias("node"))
        border = F.lit(False)
        for i, t in zip(("ix", "iy", "iz"), tile, strict=True):
            border = border | F.pmod(F.col(i), F.lit(t)).isin(0, t - 1)
        found = components(_touching(own.where(border), connectivity))  # only the surfaces of tiles meet
        roots = own.join(found, "node", "left").select("step", "voxel", F.pmod(F.coalesce("component", "node"), F.lit(grid.voxels)).alias("root"))
    else:
        raise ValueError(engine)
    return numbered(roots).select("step", "voxel", *[c.alias(k) for k, c in grid.indices().items()], "bubble")


def _node(grid: GridSpec) -> Column:
    return F.col("step").cast("long") * F.lit(grid.voxels) + F.col("voxel")


def _local(n: tuple[int, int, int], connectivity: int, keys: list[str]):
    def run(table: pa.Table) -> pa.Table:
        voxel = table.column("voxel").to_numpy()
        return pa.table({**{k: table.column(k) for k in keys}, "voxel": table.column("voxel"), "root": pa.array(label_voxels(voxel, n, connectivity))})

    return run
