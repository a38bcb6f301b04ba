"""General operators that the methods are made of."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.shared import asof


def bucketed_range_join(left: DataFrame, right: DataFrame, left_pos: list[str], right_pos: list[str], radius: list[float], cell: list[float]) -> DataFrame:
    """Pairs whose positions differ by at most `radius` on each axis, by an equi-join on cells that `right` reaches."""
    for i, (p, r, c) in enumerate(zip(right_pos, radius, cell, strict=True)):
        right = right.withColumn(f"_k{i}", F.explode(F.sequence(F.floor((F.col(p) - r) / c), F.floor((F.col(p) + r) / c))))
    for i, (p, c) in enumerate(zip(left_pos, cell, strict=True)):
        left = left.withColumn(f"_k{i}", F.floor(F.col(p) / c))
    keys = [f"_k{i}" for i in range(len(cell))]
    test = F.lit(True)
    for a, b, r in zip(left_pos, right_pos, radius, strict=True):
        test = test & (F.abs(F.col(a) - F.col(b)) <= r)
    return left.join(right, keys).where(test).drop(*keys)


def asof_join(left: DataFrame, right: DataFrame, on: str, by: list[str]) -> DataFrame:
    return asof(left, right, on, by)


def densify(df: DataFrame, keys: list[str], lattice: DataFrame, fill: dict[str, float]) -> DataFrame:
    """All rows of `lattice`, with what `df` has for them and `fill` for the others."""
    return lattice.join(df, keys, "left").na.fill(fill)


def top_k(df: DataFrame, by: str, k: int, per: list[str] | None = None, tie: str = "bubble") -> DataFrame:
    """The k rows with the greatest `by`, of all or of each group; without a total sort."""
    if not per:
        return df.orderBy(F.desc(by), tie).limit(k)
    return df.withColumn("_r", F.row_number().over(Window.partitionBy(*per).orderBy(F.desc(by), tie))).where(F.col("_r") <= k).drop("_r")


def unpivot(df: DataFrame, ids: list[str], cols: list[str]) -> DataFrame:
    return df.select(*ids, *[F.col(c).cast("double").alias(c) for c in cols]).unpivot(ids, cols, "name", "value")


def rollup_counts(df: DataFrame, keys: list[str], value: Column | None = None) -> DataFrame:
    return df.rollup(*keys).agg(F.count(F.lit(1)).alias("n") if value is None else F.sum(value).alias("n"))


def cube_counts(df: DataFrame, keys: list[str], value: Column | None = None) -> DataFrame:
    return df.cube(*keys).agg(F.count(F.lit(1)).alias("n") if value is None else F.sum(value).alias("n"))


def moving(df: DataFrame, key: str, order: str, value: str, back: int, ahead: int) -> DataFrame:
    """Adds moving_mean over rows whose `order` lies in the range around each row's own."""
    w = Window.partitionBy(key).orderBy(order).rangeBetween(-back, ahead)
    return df.withColumn("moving_mean", F.avg(value).over(w))


def moving_tail(df: DataFrame, order: str, value: str) -> DataFrame:
    """Adds the running share of `value`: grouped sums first, so that only groups stand in one sequence."""
    w = Window.orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    sums = df.groupBy(order).agg(F.sum(value).alias("s"))
    return sums.withColumn("running", F.sum("s").over(w))


def interval_join(points: DataFrame, intervals: DataFrame, at: str, lo: str, hi: str, width: int = 16) -> DataFrame:
    """Points with every interval [lo, hi] that holds them (whole numbers): an equi-join on stretches of `width`, and the test."""
    cells = intervals.withColumn("_k", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_k", F.floor(F.col(at) / width)).join(cells, "_k").where(F.col(at).between(F.col(lo), F.col(hi))).drop("_k")


def sampled(df: DataFrame, share: float, seed: int = 1, by: str | None = None, shares: dict | None = None) -> DataFrame:
    """A quick look at a share of the rows, or at shares by the value of a column; the same rows in every run over the same files."""
    return df.sampleBy(by, shares, seed) if by is not None else df.sample(fraction=share, seed=seed)
