"""Whole runs: particles to fields while a simulation goes on, fields to bubbles and tracks after it."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import SIGMA_FLOOR, GridSpec, Target
from ..operators import components, density, gaussian, lifecycle, segment, similarity, supervoxel, track, traits
from ..sources import fields as store_fields
from ..sources.shared import store


def accessed(particles: DataFrame, start: int | None = None, count: int | None = None, stride: int = 1) -> DataFrame:
    """Steps that are looked at: from `start` on, `count` steps long, every `stride`-th."""
    out = particles
    first = 0 if start is None else start
    if start is not None:
        out = out.where(F.col("step") >= start)
    if count is not None:
        out = out.where(F.col("step") < first + count)
    return out.where((F.col("step") - first) % stride == 0) if stride > 1 else out


class InSitu(NamedTuple):
    fields: DataFrame  # step, voxel, similarity, rise_velocity
    density: DataFrame
    labels: DataFrame
    gaussians: DataFrame
    report: DataFrame


def in_situ(particles: DataFrame, grid: GridSpec, target: Target, stride: int = 1, start: int | None = None, count: int | None = None, size: tuple[int, int, int] = (3, 3, 3), gamma: float = 0.3, max_iter: int = 20, engine: str = "array", norm: str = "max", spread: str = "std", sigma_floor: float = SIGMA_FLOOR, scope: str = "step") -> InSitu:
    """One scan of the particles for densities and velocities; all after it works on the small fields, step by step at once.

    "array" makes all fields of a step in the task that gets its histogram. "relational" joins fields over all
    steps, for grids beyond a task and for scores over the whole run (scope="run").
    """
    target.check(grid)
    hist = density.histogram(accessed(particles, start, count, stride), grid)
    if engine == "array" and scope == "step":
        return of_histogram(hist, grid, target, size, gamma, max_iter, norm, spread, sigma_floor)
    field = store(density.density_field(hist, grid), "density")
    labels, _, report = supervoxel.slic(field, grid, size, gamma, max_iter, engine)
    gaussians = gaussian.fit_clusters(labels, field, sigma_floor)
    bsf = similarity.bsf(labels, gaussians, target, norm=norm, scope=scope, spread=spread)
    out = bsf.join(field.select("step", "voxel", "rise_velocity"), ["step", "voxel"])
    return InSitu(out, field, labels, gaussians, report)


def of_histogram(hist: DataFrame, grid: GridSpec, target: Target, size: tuple[int, int, int] = (3, 3, 3), gamma: float = 0.3, max_iter: int = 20, norm: str = "max", spread: str = "std", sigma_floor: float = SIGMA_FLOOR) -> InSitu:
    """All fields of each step from its histogram, in one task a step; nothing of a voxel is shuffled afterwards."""

    def run(table: pa.Table) -> pa.Table:
        voxel = table.column("voxel").to_numpy()
        count, speed = np.zeros(grid.voxels, np.int64), np.full(grid.voxels, np.nan)
        count[voxel] = table.column("n").to_numpy()
        speed[voxel] = table.column("sum_vx").to_numpy() / count[voxel]
        label, centre, report = supervoxel.cluster_arrays(count.reshape(grid.n), size, gamma, max_iter)
        n, s1, s2 = (np.bincount(label, w, len(centre)).astype(np.int64) for w in (None, count, count * count))
        there = np.flatnonzero(n)
        mu, sigma = gaussian.of_sums(n[there], s1[there], s2[there], sigma_floor)
        score = np.zeros(len(centre))
        distance = similarity.distance_array(mu, sigma, target, spread)
        score[there] = similarity.score_array(distance, norm)
        lists = {
            "voxels": supervoxel.structs(voxel=np.arange(grid.voxels), cluster=label.astype(np.int32), density=count, rise_velocity=pa.array(speed, mask=np.isnan(speed)), similarity=score[label]),
            "gaussians": supervoxel.structs(cluster=there.astype(np.int32), mu=mu, sigma=sigma, n=n[there]),
            "report": supervoxel.report_rows(report),
        }
        return pa.table({"step": pa.array([table.column("step")[0].as_py()], pa.int32()), **lists})

    schema = f"step int, voxels array<struct<voxel:bigint,cluster:int,density:bigint,rise_velocity:double,similarity:double>>, gaussians array<struct<cluster:int,mu:double,sigma:double,n:bigint>>, report {supervoxel.REPORT}"
    named = hist.select(F.col("step").cast("int").alias("step"), grid.voxel().alias("voxel"), "n", F.col("sum_vx").cast("double").alias("sum_vx"))
    packed = store(named.groupBy("step").applyInArrow(run, schema), "in-situ")
    voxels = packed.select("step", F.inline("voxels"))
    indices = [c.alias(k) for k, c in grid.indices().items()]
    return InSitu(
        voxels.select("step", "voxel", "similarity", "rise_velocity"),
        voxels.select("step", "voxel", *indices, "density", "rise_velocity"),
        voxels.select("step", "voxel", "cluster"),
        packed.select("step", F.inline("gaussians")),
        packed.select("step", F.inline("report")),
    )


class PostHoc(NamedTuple):
    labels: DataFrame
    traits: DataFrame
    edges: DataFrame
    tracks: DataFrame


def post_hoc(fields: DataFrame, grid: GridSpec, threshold: float = segment.THRESHOLD, connectivity: int = 6, min_voxels: int = 1, dt: float = 1.0, keep_freeboard: bool = False, engine: str = "local") -> PostHoc:
    """Bubbles, what they are like, how they overlap, and all tracks with velocities and events. engine: of the components."""
    labels = store(components.label(segment.by_similarity(fields, threshold), grid, connectivity, engine), "labels")
    what = traits.describe(labels, grid).where(F.col("voxels") >= min_voxels)
    what = store(what if keep_freeboard else what.where("not is_freeboard"), "traits")
    labels = store(labels.join(what.select("step", "bubble"), ["step", "bubble"], "left_semi"), "bubbles")
    edges = store(track.measured(track.overlaps(labels)), "edges")
    tracks = track.with_traits(track.all_tracks(edges, what), what)
    tracks = lifecycle.volume_events(track.flag_low_confidence(track.rise_velocity(tracks, dt)))
    return PostHoc(labels, what, edges, tracks)


def ensemble(particles: DataFrame, grid: GridSpec, member: str = "member") -> DataFrame:
    """member, step, ix, iy, iz, n, sum_vx: the histograms of all runs of an ensemble in one scan."""
    return density.histogram(particles, grid, keys=(member,))


def register(spark: SparkSession, **tables: DataFrame) -> None:
    """The tables of a run as temporary views for SQL."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)


def run_in_situ_to(path: str, particles: DataFrame, grid: GridSpec, target: Target, **options) -> DataFrame:
    store_fields.write_fields(in_situ(particles, grid, target, **options).fields, path)
    return store_fields.read_fields(particles.sparkSession, path)


def from_raw(path: str, grid: GridSpec, target: Target, spark: SparkSession, parallelism: int | None = None, **options) -> InSitu:
    """The workflow on stored raw particles: read them all back, then the same computation."""
    raw = spark.read.parquet(path)
    return in_situ(raw.repartition(parallelism, "step") if parallelism else raw, grid, target, **options)
