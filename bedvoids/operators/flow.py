"""How particles move around bubbles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import GridSpec


def around(labels: DataFrame, field: DataFrame, grid: GridSpec, shell: int = 2) -> DataFrame:
    """step, bubble, region, voxels, mean_rise, up_share, down_share for below, above and sides of each bubble.

    Regions are parts of the bubble's box widened by `shell` voxels. Boxes are spread over the voxels they
    hold, so the field meets them by equality of step and voxel, and only near bubbles.
    """
    box = labels.groupBy("step", "bubble").agg(*[f(i).alias(f"{i}_{n}") for i in ("ix", "iy", "iz") for n, f in (("lo", F.min), ("hi", F.max))])
    for i, n in zip(("ix", "iz"), (grid.n[0], grid.n[2]), strict=True):
        box = box.withColumn(i, F.explode(F.sequence(F.greatest(F.col(f"{i}_lo") - shell, F.lit(0)), F.least(F.col(f"{i}_hi") + shell, F.lit(n - 1)))))
    box = box.withColumn("iy", F.explode(F.sequence("iy_lo", "iy_hi")))
    within = F.col("iz").between(F.col("iz_lo"), F.col("iz_hi"))
    region = F.when((F.col("ix") < F.col("ix_lo")) & within, "below").when((F.col("ix") > F.col("ix_hi")) & within, "above").when(F.col("ix").between(F.col("ix_lo"), F.col("ix_hi")) & ~within, "side")
    near = box.withColumn("region", region).where("region is not null").select("step", "bubble", "region", grid.voxel().alias("voxel"))
    taken = labels.select("step", "voxel").distinct()
    seen = near.join(taken, ["step", "voxel"], "left_anti").join(field.select("step", "voxel", "rise_velocity").where("rise_velocity is not null"), ["step", "voxel"])
    v = F.col("rise_velocity")
    n = F.count(F.lit(1))
    return seen.groupBy("step", "bubble", "region").agg(n.alias("voxels"), F.avg(v).alias("mean_rise"), (F.count_if(v > 0) / n).alias("up_share"), (F.count_if(v < 0) / n).alias("down_share"))


def wake_contrast(near: DataFrame) -> DataFrame:
    """step, bubble, below, above, side, contrast: how much faster particles rise right below a bubble than right above."""
    wide = near.groupBy("step", "bubble").pivot("region", ["below", "above", "side"]).agg(F.first("mean_rise"))
    return wide.withColumn("contrast", F.col("below") - F.col("above"))
