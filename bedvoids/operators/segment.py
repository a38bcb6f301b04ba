"""From similarity fields to segmented voxels."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.grid import GridSpec

THRESHOLD = 0.92


def by_similarity(bsf: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    return bsf.where(F.col("similarity") >= threshold)


def sweep(bsf: DataFrame, thresholds: list[float]) -> DataFrame:
    """Segmented voxels at each threshold, in one pass."""
    rows = F.explode(F.filter(F.array(*map(F.lit, thresholds)), lambda t: F.col("similarity") >= t))
    return bsf.select("step", "voxel", "similarity", rows.alias("threshold"))


def levels(bsf: DataFrame, at: list[float]) -> DataFrame:
    """step, voxel, level: the highest of the nested levels that a voxel reaches."""
    level = F.array_max(F.filter(F.array(*map(F.lit, at)), lambda t: F.col("similarity") >= t))
    return bsf.select("step", "voxel", level.alias("level")).where("level is not null")


def threshold_profile(bsf: DataFrame, bins: int = 20) -> DataFrame:
    """step, bin, voxels, above: how many voxels lie in each bin of similarity, and in it or above."""
    b = F.least(F.floor(F.col("similarity") * bins), F.lit(bins - 1)).cast("int")
    hist = bsf.groupBy("step", b.alias("bin")).agg(F.count(F.lit(1)).alias("voxels"))
    w = Window.partitionBy("step").orderBy(F.desc("bin")).rowsBetween(Window.unboundedPreceding, 0)
    return hist.withColumn("above", F.sum("voxels").over(w))


def flag_freeboard(labels: DataFrame, grid: GridSpec, min_span_fraction: float = 0.0) -> DataFrame:
    """step, bubble, is_freeboard: whether a component holds voxels of the top layer (that share of it, if given)."""
    top = F.count_if(F.col("ix") == grid.n[0] - 1)
    need = max(1.0, min_span_fraction * grid.n[1] * grid.n[2])
    return labels.groupBy("step", "bubble").agg((top >= need).alias("is_freeboard"))
