"""What a bubble is like: volume, place, shape."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import GridSpec


def describe(labels: DataFrame, grid: GridSpec, bsf: DataFrame | None = None, width_axis: str = "z", moments: bool = False, unit: str = "voxel") -> DataFrame:
    """A row for each bubble. With `bsf` centroids are weighted by similarity; `moments` adds the aspect of second moments.

    Aspect is width by height; height lies along x, width along z, y or the larger of both, in voxels or
    (unit="world") in the units of the grid's axes.
    """
    rows = labels.select("step", "bubble", "voxel", "ix", "iy", "iz")
    w = F.lit(1.0)
    scale = (1.0, 1.0, 1.0) if unit == "voxel" else grid.widths
    if bsf is not None:
        rows = rows.join(bsf.select("step", "voxel", "similarity"), ["step", "voxel"])
        w = F.col("similarity")
    centre = [(F.sum(w * grid.centre(i)) / F.sum(w)).alias(f"{a}c") for i, a in enumerate("xyz")] if bsf is not None else [(F.lit(grid.lo[i]) + (F.sum(f"i{a}") / F.count(F.lit(1)) + F.lit(0.5)) * F.lit(grid.widths[i])).alias(f"{a}c") for i, a in enumerate("xyz")]
    ends = [f(f"i{a}").alias(f"i{a}_{n}") for a in "xyz" for n, f in (("min", F.min), ("max", F.max))]
    spread = [F.var_pop(f"i{a}").alias(f"_v{a}") for a in "xyz"] if moments else []
    out = rows.groupBy("step", "bubble").agg(F.count(F.lit(1)).alias("voxels"), *centre, *ends, *spread)
    extent = {a: (F.col(f"i{a}_max") - F.col(f"i{a}_min") + 1) * F.lit(scale[i]) for i, a in enumerate("xyz")}
    width = F.greatest(extent["y"], extent["z"]) if width_axis == "max" else extent[width_axis]
    cols = [c for c in out.columns if not c.startswith("_v")]
    more = [(F.sqrt(F.col("_vz") + F.lit(1 / 12)) * F.lit(scale[2]) / (F.sqrt(F.col("_vx") + F.lit(1 / 12)) * F.lit(scale[0]))).alias("aspect_moments")] if moments else []
    return out.select(*cols, (F.col("voxels") * F.lit(grid.voxel_volume)).alias("volume"), (width / extent["x"]).alias("aspect"), (F.col("ix_max") == grid.n[0] - 1).alias("is_freeboard"), *more)


def enrich(labels: DataFrame, bsf: DataFrame, pvf: DataFrame) -> DataFrame:
    """step, bubble, mean_similarity, mean_rise: what the fields say inside each bubble."""
    both = labels.join(bsf.select("step", "voxel", "similarity"), ["step", "voxel"], "left").join(pvf.select("step", "voxel", "rise_velocity"), ["step", "voxel"], "left")
    return both.groupBy("step", "bubble").agg(F.avg("similarity").alias("mean_similarity"), F.avg("rise_velocity").alias("mean_rise"))
