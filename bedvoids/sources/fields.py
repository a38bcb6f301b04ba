"""Fields on disk, and their packed form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import GridSpec
from .shared import bytes_of


def pack(df: DataFrame, grid: GridSpec, values: list[str]) -> DataFrame:
    """One row for each step with arrays of all voxels in order; what is missing is null."""
    rows = df.select("step", "voxel", *[F.col(v).cast("float").alias(v) for v in values])
    lattice = df.select("step").distinct().select("step", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(grid.voxels - 1).cast("long"))).alias("voxel"))
    every = lattice.join(rows, ["step", "voxel"], "left")
    inorder = every.groupBy("step").agg(F.array_sort(F.collect_list(F.struct("voxel", *values))).alias("m"))
    nx, ny, nz = grid.n
    return inorder.select("step", F.lit(0).alias("tile"), F.lit(nx).alias("nx"), F.lit(ny).alias("ny"), F.lit(nz).alias("nz"), *[F.col(f"m.{v}").alias(v) for v in values])


def unpack(packed: DataFrame, values: list[str]) -> DataFrame:
    """step, voxel and one column for each array."""
    rows = packed.select("step", F.posexplode(F.arrays_zip(*values)).alias("voxel", "v"))
    return rows.select("step", F.col("voxel").cast("long").alias("voxel"), *[F.col(f"v.{v}").alias(v) for v in values])


def write_fields(fields: DataFrame, path: str) -> None:
    """By step; writing a step again replaces it and leaves the others."""
    fields.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("step").parquet(path)


def read_fields(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def write_distribution(gaussians: DataFrame, labels: DataFrame, path: str) -> None:
    """The distribution field itself: Gaussians and labels instead of a scalar for each voxel."""
    write_fields(gaussians.select("step", "cluster", "mu", "sigma", "n"), f"{path}/gaussians")
    write_fields(labels.select("step", "voxel", "cluster"), f"{path}/labels")


def write_raw(particles: DataFrame, path: str) -> None:
    particles.write.mode("overwrite").partitionBy("step").parquet(path)


def write_view(spec: DataFrame, path: str) -> None:
    """The description of a view or scene as JSON lines."""
    spec.write.mode("overwrite").json(path)


def field_bytes(spark: SparkSession, paths: dict[str, str]) -> DataFrame:
    """what, bytes: files of a distribution, a field or raw rows, for comparison."""
    return spark.createDataFrame([(k, bytes_of(spark, p)) for k, p in paths.items()], "what string, bytes long")
