"""What the methods are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import INDEX, GridSpec
from .supervoxel import block_label, structs


def density_threshold(field: DataFrame, at_most: float = 12) -> DataFrame:
    """Segmented voxels by a fixed density."""
    return field.where(F.col("density") <= at_most).select("step", "voxel")


def void_fraction(field: DataFrame, max_count: float) -> DataFrame:
    """step, voxel, void_fraction: share of a bin that particles leave free; `max_count` of them fill it."""
    return field.select("step", "voxel", F.greatest(F.lit(1.0) - F.col("density") / F.lit(float(max_count)), F.lit(0.0)).alias("void_fraction"))


def void_fraction_threshold(field: DataFrame, max_count: float, t: float) -> DataFrame:
    return void_fraction(field, max_count).where(F.col("void_fraction") >= t).select("step", "voxel")


def box_overlaps(traits: DataFrame, gap: int = 1) -> DataFrame:
    """step, src, dst: bubbles of consecutive steps whose bounding boxes meet. Boxes meet by cells they share, not all with all."""
    cell = 8
    ends = [f"i{a}_{n}" for a in "xyz" for n in ("min", "max")]
    cells = lambda df: df.select("*", F.explode(F.sequence(F.floor(F.col("ix_min") / cell).cast("int"), F.floor(F.col("ix_max") / cell).cast("int"))).alias("kx")).select("*", F.explode(F.sequence(F.floor(F.col("iz_min") / cell).cast("int"), F.floor(F.col("iz_max") / cell).cast("int"))).alias("kz"))
    a = cells(traits.select("step", F.col("bubble").alias("src"), *ends))
    b = cells(traits.select((F.col("step") - gap).alias("step"), F.col("bubble").alias("dst"), *ends))
    test = F.lit(True)
    for x in "xyz":
        test = test & (F.col(f"a.i{x}_min") <= F.col(f"b.i{x}_max")) & (F.col(f"b.i{x}_min") <= F.col(f"a.i{x}_max"))
    return a.alias("a").join(b.alias("b"), ["step", "kx", "kz"]).where(test).select("step", "src", "dst").distinct()


def overlap_links(edges: DataFrame, which: str = "any") -> DataFrame:
    """Links without confidence: any overlap, or the largest one of each bubble."""
    if which == "any":
        return edges.select("step", "src", "dst", "inter")
    best = edges.groupBy("step", "src").agg(F.min_by("dst", F.struct(-F.col("inter"), F.col("dst"))).alias("dst"), F.max("inter").alias("inter"))
    return best.select("step", "src", "dst", "inter")


def blocks(field: DataFrame, grid: GridSpec, size: tuple[int, int, int] = (3, 3, 3)) -> DataFrame:
    """step, voxel, cluster of a regular partition."""
    return field.select("step", "voxel", block_label(grid, size).alias("cluster"))


def kmeans(field: DataFrame, grid: GridSpec, k: int, gamma: float = 0.3, max_iter: int = 20) -> tuple[DataFrame, DataFrame]:
    """Global K-means with the mixed distance, every voxel with every centre: labels and report (distances). For small grids."""

    def run(table: pa.Table) -> pa.Table:
        voxel, value = table.column("voxel").to_numpy(), table.column("density").to_numpy().astype(float)
        pos = np.stack([table.column(i).to_numpy() for i in INDEX], 1).astype(float)
        order = np.argsort(voxel)
        voxel, value, pos = voxel[order], value[order], pos[order]
        start = np.linspace(0, len(voxel) - 1, k).round().astype(int)
        centre, cv, label, report = pos[start], value[start], np.full(len(voxel), -1), []
        for i in range(max_iter):
            nearest = [(gamma * np.sqrt(((pos[j : j + 1024, None] - centre[None]) ** 2).sum(2)) + (1 - gamma) * np.abs(value[j : j + 1024, None] - cv[None])).argmin(1) for j in range(0, len(voxel), 1024)]
            new = np.concatenate(nearest)
            changed = int((new != label).sum())
            label = new
            report.append({"iteration": i + 1, "changed": changed, "distances": len(voxel) * k})
            n = np.maximum(np.bincount(label, minlength=k), 1)
            there = np.bincount(label, minlength=k) > 0
            centre = np.where(there[:, None], np.stack([np.bincount(label, pos[:, j], minlength=k) / n for j in range(3)], 1), centre)
            cv = np.where(there, np.bincount(label, value, minlength=k) / n, cv)
            if not changed:
                break
        return pa.table({"step": table.column("step").slice(0, 1).cast(pa.int32()), "labels": structs(voxel=voxel, cluster=label.astype(np.int32)), "report": pa.array([report], pa.list_(pa.struct([("iteration", pa.int32()), ("changed", pa.int64()), ("distances", pa.int64())])))})

    packed = field.select("step", "voxel", *INDEX, "density").groupBy("step").applyInArrow(run, "step int, labels array<struct<voxel:bigint,cluster:int>>, report array<struct<iteration:int,changed:bigint,distances:bigint>>")
    return packed.select("step", F.inline("labels")), packed.select("step", F.inline("report"))


def strided(particles: DataFrame, every: int = 50) -> DataFrame:
    """The steps that a strided dump of raw particles keeps."""
    return particles.where(F.col("step") % every == 0)
