"""The example region and its Gaussian."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.grid import SIGMA_FLOOR, Box, GridSpec, Target
from . import gaussian


def select_box(field: DataFrame, box: Box, step: int) -> DataFrame:
    return field.where((F.col("step") == step) & box.test())


def box_gaussian(field: DataFrame, box: Box, step: int, sigma_floor: float = SIGMA_FLOOR) -> DataFrame:
    """mu, sigma, n of the densities in the box."""
    inside = select_box(field, box, step)
    return gaussian.of_moments(inside.agg(*gaussian.moments()), sigma_floor)


def fit_target(field: DataFrame, box: Box, step: int, sigma_floor: float = SIGMA_FLOOR, grid: GridSpec | None = None) -> Target:
    row = box_gaussian(field, box, step, sigma_floor).first()
    if not row["n"]:
        raise ValueError("the box holds no voxel")
    return Target(row["mu"], row["sigma"], row["n"], grid)
