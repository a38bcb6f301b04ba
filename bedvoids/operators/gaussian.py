"""Gaussians of clusters, from moments that add up."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.grid import SIGMA_FLOOR


def moments(value: str = "density") -> list[Column]:
    v = F.col(value)
    return [F.count(F.lit(1)).alias("n"), F.sum(v).alias("s1"), F.sum(v * v).alias("s2")]


def merge(parts: DataFrame, keys: list[str]) -> DataFrame:
    """Moments of parts (tiles, batches) put together."""
    return parts.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in ("n", "s1", "s2")])


def of_moments(parts: DataFrame, sigma_floor: float = SIGMA_FLOOR) -> DataFrame:
    """mu and sigma from counts, sums and sums of squares of whole numbers: exact up to the last division and root."""
    mu = F.col("s1") / F.col("n")
    var = (F.col("s2") * F.col("n") - F.col("s1") * F.col("s1")).cast("double") / (F.col("n") * F.col("n"))
    keys = [c for c in parts.columns if c not in ("n", "s1", "s2")]
    return parts.select(*keys, mu.alias("mu"), F.greatest(F.sqrt(var), F.lit(sigma_floor)).alias("sigma"), "n")


def of_sums(n: np.ndarray, s1: np.ndarray, s2: np.ndarray, sigma_floor: float = SIGMA_FLOOR) -> tuple[np.ndarray, np.ndarray]:
    """The same from arrays of whole numbers."""
    return s1 / n, np.maximum(np.sqrt((s2 * n - s1 * s1).astype(float) / (n * n)), sigma_floor)


def fit_clusters(labels: DataFrame, field: DataFrame, sigma_floor: float = SIGMA_FLOOR) -> DataFrame:
    """step, cluster, mu, sigma, n from (step, voxel, cluster) and the field."""
    both = labels.select("step", "voxel", "cluster").join(field.select("step", "voxel", "density"), ["step", "voxel"])
    return of_moments(both.groupBy("step", "cluster").agg(*moments()), sigma_floor)


def fit_vectors(vectors: DataFrame, key: str, cols: list[str], floor: float = 1e-9) -> DataFrame:
    """key, mu, cov, n: Gaussians of several dimensions (cov row by row), by sums of products."""
    pairs = [(a, b) for i, a in enumerate(cols) for b in cols[i:]]
    agg = vectors.groupBy(key).agg(F.count(F.lit(1)).alias("n"), *[F.avg(c).alias(f"m_{c}") for c in cols], *[F.covar_pop(a, b).alias(f"c_{a}_{b}") for a, b in pairs])
    entry = lambda a, b: (F.col(f"c_{a}_{b}" if (a, b) in pairs else f"c_{b}_{a}") + F.lit(floor if a == b else 0.0))
    return agg.select(key, F.array(*[f"m_{c}" for c in cols]).alias("mu"), F.array(*[entry(a, b) for a in cols for b in cols]).alias("cov"), "n")


def reference_moments(values: pd.Series) -> tuple[float, float]:
    return float(np.mean(values)), float(np.std(values))
