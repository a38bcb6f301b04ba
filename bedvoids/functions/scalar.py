"""Distances, similarities and their SQL names, as column expressions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from .grid import Target


def mixed_distance(pos: list[tuple[Column, Column]], value: tuple[Column, Column], gamma: float) -> Column:
    """gamma times the Euclidean distance of positions plus the rest times the difference of values."""
    squares = None
    for a, b in pos:
        d = (a - b) * (a - b)
        squares = d if squares is None else squares + d
    return F.lit(float(gamma)) * F.sqrt(squares) + F.lit(float(1 - gamma)) * F.abs(value[0] - value[1])


def bhattacharyya(mu: Column, sigma: Column, target: Target, spread: str = "std") -> Column:
    """Distance of Gaussians in closed form. spread: whether standard deviations or variances stand in its two terms."""
    if spread not in ("std", "var"):
        raise ValueError(spread)
    a = sigma if spread == "std" else sigma * sigma
    b = F.lit(float(target.sigma if spread == "std" else target.sigma * target.sigma))
    half = (a + b) / F.lit(2.0)
    d = mu - F.lit(float(target.mu))
    return d * d / half / F.lit(8.0) + F.lit(0.5) * F.log(half / F.sqrt(a * b))


def bhattacharyya_many(mu_a: np.ndarray, cov_a: np.ndarray, mu_b: np.ndarray, cov_b: np.ndarray) -> float:
    """The same for several dimensions, with covariance matrices."""
    half = (cov_a + cov_b) / 2
    d = mu_a - mu_b
    return float(d @ np.linalg.solve(half, d) / 8 + 0.5 * (np.linalg.slogdet(half)[1] - 0.5 * (np.linalg.slogdet(cov_a)[1] + np.linalg.slogdet(cov_b)[1])))


def bhattacharyya_mv():
    """Arrow function of (mu_a, cov_a, mu_b, cov_b): arrays of numbers, matrices as rows one after another."""

    def run(parts: Iterator[tuple[pd.Series, pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for mu_a, cov_a, mu_b, cov_b in parts:
            square = lambda c, m: np.asarray(c, float).reshape(len(m), len(m))
            yield pd.Series([bhattacharyya_many(np.asarray(a, float), square(p, a), np.asarray(b, float), square(q, b)) for a, p, b, q in zip(mu_a, cov_a, mu_b, cov_b, strict=True)], dtype=float)

    return F.pandas_udf(run, "double")


def dice(inter: Column, a: Column, b: Column) -> Column:
    return F.lit(2.0) * inter / (a + b)


def jaccard(inter: Column, a: Column, b: Column) -> Column:
    return inter / (a + b - inter)


def overlap_coefficient(inter: Column, a: Column, b: Column) -> Column:
    return inter / F.least(a, b)


def dice_of_sets(a: Column, b: Column) -> Column:
    return dice(F.size(F.array_intersect(a, b)), F.size(F.array_distinct(a)), F.size(F.array_distinct(b)))


def dice_reference():
    """Grouped Arrow aggregate of two 0/1 columns, member of a and member of b: Dice; slow, to compare with."""

    def run(a: pd.Series, b: pd.Series) -> float:
        return float(2 * ((a > 0) & (b > 0)).sum() / ((a > 0).sum() + (b > 0).sum()))

    return F.pandas_udf(run, "double")


def register_sql(spark: SparkSession) -> None:
    """The scalar functions as temporary SQL functions of the session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dice(inter BIGINT, a BIGINT, b BIGINT) RETURNS DOUBLE RETURN 2.0D * inter / (a + b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION jaccard(inter BIGINT, a BIGINT, b BIGINT) RETURNS DOUBLE RETURN CAST(inter AS DOUBLE) / (a + b - inter)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mixed_distance(d DOUBLE, v DOUBLE, gamma DOUBLE) RETURNS DOUBLE RETURN gamma * d + (1.0D - gamma) * abs(v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bhattacharyya(mu DOUBLE, s DOUBLE, mu0 DOUBLE, s0 DOUBLE) RETURNS DOUBLE RETURN (mu - mu0) * (mu - mu0) / ((s + s0) / 2.0D) / 8.0D + 0.5D * ln((s + s0) / 2.0D / sqrt(s * s0))")
