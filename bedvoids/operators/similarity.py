"""The similarity field: each cluster's distance to the target, turned into a score and painted on its voxels."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.grid import Target
from ..functions.scalar import bhattacharyya


def distances(gaussians: DataFrame, target: Target, spread: str = "std", digits: int = 9) -> DataFrame:
    """Adds `distance`, rounded so that thresholds don't hang on the last bit of a logarithm."""
    return gaussians.withColumn("distance", F.round(bhattacharyya(F.col("mu"), F.col("sigma"), target, spread), digits))


def distance_array(mu: np.ndarray, sigma: np.ndarray, target: Target, spread: str = "std", digits: int = 9) -> np.ndarray:
    """The distances of `distances` from arrays."""
    a, b = (sigma, target.sigma) if spread == "std" else (sigma * sigma, target.sigma * target.sigma)
    half = (a + b) / 2.0
    d = mu - target.mu
    return np.round(d * d / half / 8.0 + 0.5 * np.log(half / np.sqrt(a * b)), digits)


def score_array(distance: np.ndarray, norm: str = "max") -> np.ndarray:
    """The scores of `scores` for one step from an array."""
    if norm == "coefficient":
        return np.exp(-distance)
    low, top = (0.0 if norm == "max" else distance.min()), distance.max()
    return 1.0 - (distance - low) / (top - low) if top > low else np.ones(len(distance))


def scores(distance: DataFrame, norm: str = "max", scope: str = "step") -> DataFrame:
    """Adds `similarity` in [0, 1]. norm: max, minmax or coefficient; scope: step, or run (which a run in progress can't know)."""
    w = Window.partitionBy(*(["step"] if scope == "step" else [F.lit(0)]))
    d, top, low = F.col("distance"), F.col("_max"), F.col("_min")
    if norm == "coefficient":
        return distance.withColumn("similarity", F.exp(-d))
    if scope == "run":
        ends = distance.agg(F.max("distance").alias("_max"), F.min("distance").alias("_min"))
        both = distance.join(F.broadcast(ends))  # one row
    else:
        both = distance.withColumn("_max", F.max("distance").over(w)).withColumn("_min", F.min("distance").over(w))
    if norm == "max":
        score = F.when(top > 0, F.lit(1.0) - d / top).otherwise(1.0)
    elif norm == "minmax":
        score = F.when(top > low, F.lit(1.0) - (d - low) / (top - low)).otherwise(1.0)
    else:
        raise ValueError(norm)
    return both.withColumn("similarity", score).drop("_max", "_min")


def bsf(labels: DataFrame, gaussians: DataFrame, target: Target, norm: str = "max", scope: str = "step", spread: str = "std") -> DataFrame:
    """step, voxel, similarity."""
    scored = scores(distances(gaussians, target, spread), norm, scope).select("step", "cluster", "similarity")
    return labels.join(scored, ["step", "cluster"]).select("step", "voxel", "similarity")
