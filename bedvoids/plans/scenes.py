"""Runs over the given tables whose results many queries look at."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import Box, GridSpec, Target, bed_grid
from ..operators import components, density, segment, target, track, traits
from ..sources import particles as P
from ..sources.shared import store
from . import pipeline

GRID = bed_grid((24, 6, 24))
#: Boxes as a user would draw them at the first step: inside the void that grows, and inside the small one.
BOXES = {"rise": Box((2, 4), (2, 3), (3, 4)), "shapes": Box((4, 4), (2, 3), (2, 2))}
#: Smaller bubbles are left out.
LEAST = 4


class Run(NamedTuple):
    """A scene in situ and after: all its steps, from the rows of a table folder."""

    grid: GridSpec
    target: Target
    field: DataFrame  # step, voxel, ix, iy, iz, density, rise_velocity
    labels: DataFrame  # step, voxel, cluster
    gaussians: DataFrame  # step, cluster, mu, sigma, n
    report: DataFrame
    bsf: DataFrame  # step, voxel, similarity, rise_velocity
    found: DataFrame  # step, voxel, ix, iy, iz, bubble: all segmented voxels, the freeboard's too
    voxels: DataFrame  # the same of the bubbles that are kept
    traits: DataFrame
    edges: DataFrame


_RUNS: dict[tuple[str, str, str], Run] = {}


def run_of(spark: SparkSession, sf_dir: str, scene: str = "rise") -> Run:
    """The run of a scene over the rows of lineitem, made once in a session and kept in the shared folder."""
    key = (spark.sparkContext.applicationId, sf_dir, scene)
    if key not in _RUNS:
        hist = store(density.histogram(P.planted_bed(spark, sf_dir, scene, GRID), GRID), "histogram")
        first = density.density_field(hist.where("step = 0"), GRID)
        goal = target.fit_target(first, BOXES[scene], 0, grid=GRID)
        made = pipeline.of_histogram(hist, GRID, goal)
        found = store(components.label(segment.by_similarity(made.fields), GRID), "found")
        what = store(traits.describe(found, GRID).where((F.col("voxels") >= LEAST) & ~F.col("is_freeboard")), "traits")
        voxels = store(found.join(what.select("step", "bubble"), ["step", "bubble"], "left_semi"), "bubbles")
        edges = store(track.measured(track.overlaps(voxels)), "edges")
        _RUNS[key] = Run(GRID, goal, made.density, made.labels, made.gaussians, made.report, made.fields, found, voxels, what, edges)
    return _RUNS[key]
