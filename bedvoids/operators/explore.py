"""Tables behind linked views: queries, parallel axes, scatterplots, scenes, comparisons."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def query(df: DataFrame, ranges: dict[str, tuple[float, float]], centred: bool = False) -> DataFrame:
    """Rows inside all ranges: (low, high), or (centre, distance) with `centred`."""
    tests = [F.col(c).between(a - b, a + b) if centred else F.col(c).between(a, b) for c, (a, b) in ranges.items()]
    return df.where(reduce(lambda p, q: p & q, tests, F.lit(True)))


def spherical(df: DataFrame, tol: float = 0.2) -> DataFrame:
    return df.where(F.abs(F.col("aspect") - 1) <= tol)


def brush(df: DataFrame, axis: str, share: float) -> DataFrame:
    """The part of the rows with the greatest values of an axis; at least `share` of them."""
    bound = df.agg(F.percentile(axis, F.lit(1 - share)).alias("_bound"))
    return df.crossJoin(F.broadcast(bound)).where(F.col(axis) >= F.col("_bound")).drop("_bound")  # one row


def parallel_axes(df: DataFrame, axes: list[str], ids: tuple[str, ...] = ("step", "bubble")) -> DataFrame:
    """ids, place, axis, value, scaled: each row's line over the axes in their order, scaled to [0, 1]."""
    ends = df.agg(*[f(a).alias(f"{a}_{n}") for a in axes for n, f in (("lo", F.min), ("hi", F.max))])
    both = df.crossJoin(F.broadcast(ends))  # one row
    point = lambda i, a: F.struct(F.lit(i).alias("place"), F.lit(a).alias("axis"), F.col(a).cast("double").alias("value"), F.when(F.col(f"{a}_hi") > F.col(f"{a}_lo"), (F.col(a) - F.col(f"{a}_lo")) / (F.col(f"{a}_hi") - F.col(f"{a}_lo"))).otherwise(0.0).cast("double").alias("scaled"))
    return both.select(*ids, F.inline(F.array(*[point(i, a) for i, a in enumerate(axes)])))


def lookup(df: DataFrame, step: int, bubble: int) -> DataFrame:
    return df.where((F.col("step") == step) & (F.col("bubble") == bubble))


def scatter(df: DataFrame, a: str, b: str, color: str | None = None, bins: int | None = None) -> DataFrame:
    """Points of two traits; with `bins` counts on a raster, for very many bubbles."""
    if bins is None:
        return df.select("step", "bubble", F.col(a).cast("double").alias("a"), F.col(b).cast("double").alias("b"), *([F.col(color).alias("color")] if color else []))
    ends = df.agg(F.min(a).alias("a0"), F.max(a).alias("a1"), F.min(b).alias("b0"), F.max(b).alias("b1"))
    place = lambda c, lo, hi: F.least(F.floor((F.col(c) - F.col(lo)) / F.greatest(F.col(hi) - F.col(lo), F.lit(1e-300)) * bins), F.lit(bins - 1)).cast("int")
    return df.crossJoin(F.broadcast(ends)).groupBy(place(a, "a0", "a1").alias("ia"), place(b, "b0", "b1").alias("ib")).agg(F.count(F.lit(1)).alias("n"))


def event_window(track: DataFrame, lo: int, hi: int) -> DataFrame:
    return track.where(F.col("step").between(lo, hi))


def splom(df: DataFrame, traits: list[str], color: str | None = "dice", ids: tuple[str, ...] = ("step", "bubble")) -> DataFrame:
    """ids, row_trait, col_trait, y, x, color: the points of the lower triangle, in one pass."""
    pairs = F.array(*[F.struct(F.lit(traits[j]).alias("row_trait"), F.lit(traits[i]).alias("col_trait"), F.col(traits[j]).cast("double").alias("y"), F.col(traits[i]).cast("double").alias("x")) for i, j in combinations(range(len(traits)), 2)])
    return df.select(*ids, *([F.col(color).alias("color")] if color else []), F.inline(pairs))


def correlations(df: DataFrame, traits: list[str], by: list[str] | None = None) -> DataFrame:
    """row_trait, col_trait, r: one aggregate over all pairs."""
    agg = df.groupBy(*(by or [])).agg(*[F.corr(F.col(traits[j]).cast("double"), F.col(traits[i]).cast("double")).alias(f"{i}_{j}") for i, j in combinations(range(len(traits)), 2)])
    rows = F.array(*[F.struct(F.lit(traits[j]).alias("row_trait"), F.lit(traits[i]).alias("col_trait"), F.col(f"{i}_{j}").alias("r")) for i, j in combinations(range(len(traits)), 2)])
    return agg.select(*(by or []), F.inline(rows))


def spread(filtered: DataFrame, images: DataFrame) -> DataFrame:
    """The images of the bubbles that a query left."""
    return images.join(filtered.select("step", "bubble").distinct(), ["step", "bubble"], "left_semi")


def scene(labels: DataFrame, track: DataFrame, pvf: DataFrame, layers: tuple[str, ...] = ("tracked", "others", "fast"), v_min: float = 2.0) -> DataFrame:
    """layer, step, voxel, value: tracked bubbles, the other bubbles, and regions of fast particles."""
    own = track.select("step", "bubble").distinct()
    parts = {
        "tracked": lambda: labels.join(own, ["step", "bubble"], "left_semi").select(F.lit("tracked").alias("layer"), "step", "voxel", F.col("bubble").cast("double").alias("value")),
        "others": lambda: labels.join(own, ["step", "bubble"], "left_anti").select(F.lit("others").alias("layer"), "step", "voxel", F.col("bubble").cast("double").alias("value")),
        "fast": lambda: pvf.where(F.col("rise_velocity") >= v_min).select(F.lit("fast").alias("layer"), "step", "voxel", F.col("rise_velocity").alias("value")),
    }
    return reduce(DataFrame.unionByName, [parts[x]() for x in layers])


def compare(tracks: DataFrame, steps: DataFrame, value: str = "volume") -> DataFrame:
    """step, track, value: every track at every step, blank where it isn't there."""
    lattice = steps.select("step").distinct().crossJoin(tracks.select("track").distinct())
    return lattice.join(tracks.groupBy("step", "track").agg(F.max(value).alias(value)), ["step", "track"], "left")


def trends(track: DataFrame) -> DataFrame:
    """track, volume_velocity_r, volume_per_step, volume_fit: how volume goes with velocity and time."""
    v, s = F.col("volume"), F.col("step").cast("double")
    return track.groupBy("track").agg(F.corr("volume", "rise_velocity").alias("volume_velocity_r"), F.regr_slope(v, s).alias("volume_per_step"), F.regr_r2(v, s).alias("volume_fit"), F.count(F.lit(1)).alias("n"))


def growth_share(tracks: DataFrame, least: int = 2) -> DataFrame:
    """grown, tracks, share: tracks of at least so many steps that end larger than they began."""
    per = tracks.groupBy("track").agg(F.min_by("volume", "step").alias("a"), F.max_by("volume", "step").alias("b"), F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
    return per.agg(F.count_if(F.col("b") > F.col("a")).alias("grown"), F.count(F.lit(1)).alias("tracks"), F.avg((F.col("b") > F.col("a")).cast("double")).alias("share"))


def velocity_by_volume_change(track: DataFrame, tol: float = 0.05) -> DataFrame:
    """direction, n, mean_velocity, mean_change: velocity and its change where volume falls, stays or grows."""
    w = Window.partitionBy("track").orderBy("step")
    change = F.col("volume") / F.lag("volume").over(w) - 1
    rows = track.withColumn("_c", F.round(change, 9)).withColumn("_d", F.col("rise_velocity") - F.lag("rise_velocity").over(w)).where("_c is not null")
    direction: Column = F.when(F.col("_c") > tol, "grows").when(F.col("_c") < -tol, "falls").otherwise("stays")
    return rows.groupBy(direction.alias("direction")).agg(F.count(F.lit(1)).alias("n"), F.avg("rise_velocity").alias("mean_velocity"), F.avg("_d").alias("mean_change"))
