"""Particles to histograms to fields."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.grid import AXES, INDEX, GridSpec


def bounds(particles: DataFrame) -> tuple[tuple[float, ...], tuple[float, ...]]:
    """Least and greatest position of all particles; skip it by declaring the bounds."""
    row = particles.agg(*[f(a).alias(f"{n}_{a}") for a in AXES for n, f in (("lo", F.min), ("hi", F.max))]).first()
    return tuple(row[f"lo_{a}"] for a in AXES), tuple(row[f"hi_{a}"] for a in AXES)


def histogram(particles: DataFrame, grid: GridSpec, axes: tuple[str, ...] = ("x",), keys: tuple[str, ...] = ()) -> DataFrame:
    """step, ix, iy, iz, n, sum_v...: counts and summed velocities of every bin that holds particles, in one scan.

    Each task sums up its own rows first; only one row for each of its bins is shuffled. `keys`: more
    columns to group by (member of an ensemble, material).
    """
    bins = grid.bins()
    binned = particles.where(grid.inside()).select(*keys, "step", grid.voxel(*[bins[i] for i in INDEX]).alias("voxel"), *[f"v{a}" for a in axes])
    sums = binned.groupBy(*keys, "step", "voxel").agg(F.count(F.lit(1)).alias("n"), *[F.sum(f"v{a}").alias(f"sum_v{a}") for a in axes])
    return sums.select(*keys, "step", *[c.alias(k) for k, c in grid.indices().items()], "n", *[f"sum_v{a}" for a in axes])


def outside(particles: DataFrame, grid: GridSpec) -> DataFrame:
    """step, outside: how many particles no bin holds."""
    return particles.groupBy("step").agg(F.count_if(~F.coalesce(grid.inside(), F.lit(False))).alias("outside"))


def coarser(hist: DataFrame, factor: int) -> DataFrame:
    """The histogram of bins `factor` times as wide, without reading particles again."""
    index = [F.floor(F.col(i) / factor).cast("int").alias(i) for i in INDEX]
    sums = [c for c in hist.columns if c.startswith("sum_")]
    keys = [c for c in hist.columns if c not in (*INDEX, "n", *sums)]
    return hist.select(*keys, *index, "n", *sums).groupBy(*keys, *INDEX).agg(F.sum("n").alias("n"), *[F.sum(c).alias(c) for c in sums])


def density_field(hist: DataFrame, grid: GridSpec, dense: bool = True, steps: DataFrame | None = None) -> DataFrame:
    """step, voxel, ix, iy, iz, density, rise_velocity. Bins without particles have density 0 and no velocity.

    `steps`: the steps to fill; by default those of the histogram.
    """
    named = hist.select("step", grid.voxel().alias("voxel"), "n", *[c for c in hist.columns if c.startswith("sum_")])
    value = F.coalesce("n", F.lit(0)).alias("density")
    speeds = [(F.col(c) / F.nullif("n", F.lit(0))).alias("rise_velocity" if c == "sum_vx" else f"velocity_{c[-1]}") for c in hist.columns if c.startswith("sum_")]
    if dense:
        steps = steps if steps is not None else hist.select("step").distinct()
        lattice = steps.select("step", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(grid.voxels - 1).cast("long"))).alias("voxel"))
        named = lattice.join(named, ["step", "voxel"], "left")
    return named.select("step", "voxel", *[c.alias(k) for k, c in grid.indices().items()], value, *speeds)


def rise_velocity_field(hist: DataFrame, grid: GridSpec, axis: str = "x", empty_velocity: float | None = None) -> DataFrame:
    """step, voxel, rise_velocity: mean velocity of each bin; bins without particles get `empty_velocity`."""
    lattice = density_field(hist.select("step", *INDEX, "n", F.col(f"sum_v{axis}").alias("sum_vx")), grid)
    return lattice.select("step", "voxel", F.coalesce("rise_velocity", F.lit(empty_velocity).cast("double")).alias("rise_velocity"))


def motion_class(speed: Column, fast: float = 2.0) -> Column:
    return F.when(speed.isNull(), "empty").when(speed >= fast, "fast").when(speed > 0, "rising").when(speed < 0, "sinking").otherwise("still")


def smooth_counts(field: DataFrame, grid: GridSpec, kernel: str = "box") -> DataFrame:
    """step, voxel, estimate: densities averaged over the 27 bins around, with equal or triangular weights."""
    weight = {"box": (1.0, 1.0), "triangle": (2.0, 1.0)}[kernel]
    near = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(c).alias("c"), F.lit(weight[abs(a)] * weight[abs(b)] * weight[abs(c)]).alias("w")) for a in (-1, 0, 1) for b in (-1, 0, 1) for c in (-1, 0, 1)])
    spread = field.select("step", "ix", "iy", "iz", "density", F.explode(near).alias("o"))
    moved = spread.select("step", *[(F.col(i) + F.col(f"o.{o}")).alias(i) for i, o in zip(INDEX, "abc", strict=True)], (F.col("density") * F.col("o.w")).alias("v"), F.col("o.w").alias("w"))
    there = moved.where(" and ".join(f"{i} between 0 and {n - 1}" for i, n in zip(INDEX, grid.n, strict=True)))
    return there.groupBy("step", grid.voxel().alias("voxel")).agg((F.sum("v") / F.sum("w")).alias("estimate"))
