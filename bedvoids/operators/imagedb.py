"""One picture of each bubble from the front, and a table that finds it."""

from __future__ import annotations

import struct
import zlib
from collections.abc import Callable, Iterator
from pathlib import Path

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.grid import GridSpec


def projection(labels: DataFrame, bsf: DataFrame | None = None, mode: str = "max") -> DataFrame:
    """step, bubble, ix, iz, value: the bubble along y; greatest or summed similarity, or voxels if there is no field."""
    if bsf is None:
        return labels.groupBy("step", "bubble", "ix", "iz").agg(F.count(F.lit(1)).cast("double").alias("value"))
    both = labels.join(bsf.select("step", "voxel", "similarity"), ["step", "voxel"])
    return both.groupBy("step", "bubble", "ix", "iz").agg((F.max if mode == "max" else F.sum)("similarity").alias("value"))


def render(labels: DataFrame, bsf: DataFrame | None, grid: GridSpec, mode: str = "max") -> DataFrame:
    """step, bubble, width, height, pixels: all bubbles in one aggregate, with one view for all; x points up."""
    nx, nz = grid.n[0], grid.n[2]
    seen = projection(labels, bsf, mode).select("step", "bubble", ((F.lit(nx - 1) - F.col("ix")) * nz + F.col("iz")).cast("int").alias("k"), F.col("value").cast("float").alias("v"))
    # the dark pixels between those that are seen come as runs
    spots = seen.groupBy("step", "bubble").agg(F.array_sort(F.collect_list(F.struct("k", "v"))).alias("m"))
    ends = F.concat(F.array(F.struct(F.lit(-1).alias("k"), F.lit(0.0).cast("float").alias("v"))), F.col("m"), F.array(F.struct(F.lit(nx * nz).alias("k"), F.lit(0.0).cast("float").alias("v"))))
    dark = F.lit(0.0).cast("float")
    runs = F.zip_with(F.slice("e", 1, F.size("e") - 1), F.slice("e", 2, F.size("e") - 1), lambda p, q: F.concat(F.when(p["k"] < 0, F.array().cast("array<float>")).otherwise(F.array(p["v"])), F.array_repeat(dark, q["k"] - p["k"] - 1)))
    return spots.withColumn("e", ends).select("step", "bubble", F.lit(nz).alias("width"), F.lit(nx).alias("height"), F.flatten(runs).alias("pixels"))


def png(width: int, height: int, pixels: list[float]) -> bytes:
    """A greyscale PNG; the brightest pixel is the greatest value."""
    top = max(pixels) or 1.0
    rows = b"".join(b"\0" + bytes(round(255 * p / top) for p in pixels[r * width : (r + 1) * width]) for r in range(height))
    part = lambda kind, data: struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))
    return b"\x89PNG\r\n\x1a\n" + part(b"IHDR", struct.pack(">IIBBBBB", width, height, 8, 0, 0, 0, 0)) + part(b"IDAT", zlib.compress(rows)) + part(b"IEND", b"")


def _png(width: pd.Series, height: pd.Series, pixels: pd.Series) -> pd.Series:
    return pd.Series([png(int(w), int(h), list(map(float, p))) for w, h, p in zip(width, height, pixels, strict=True)])


def pictures(images: DataFrame) -> DataFrame:
    """step, bubble, png."""
    return images.select("step", "bubble", F.pandas_udf(_png, "binary")("width", "height", "pixels").alias("png"))


def index(traits: DataFrame) -> DataFrame:
    """The attribute table with the name of each bubble's picture in FILE."""
    return traits.withColumn("FILE", file_name())


def file_name() -> Column:
    return F.format_string("step_%06d/bubble_%06d.png", F.col("step"), F.col("bubble"))


def write(images: DataFrame, traits: DataFrame, path: str) -> None:
    """A PNG for each bubble under the name that the table has in FILE, and the table as one CSV file with a header."""
    named = pictures(images).withColumn("FILE", file_name())
    root = path.removeprefix("file://")
    if "://" in root:  # a store that only Spark writes to: the pictures stay rows, by their names
        named.select("FILE", "png").write.mode("overwrite").parquet(f"{path}/images")
    else:
        named.select("FILE", "png").foreachPartition(_files(f"{root}/images"))
    index(traits).coalesce(1).write.mode("overwrite").option("header", True).csv(f"{path}/index")


def _files(root: str) -> Callable:
    def put(rows: Iterator) -> None:
        for r in rows:
            place = Path(root, r["FILE"])
            place.parent.mkdir(parents=True, exist_ok=True)
            place.with_suffix(".tmp").write_bytes(r["png"])
            place.with_suffix(".tmp").replace(place)  # a task that runs again replaces the picture

    return put
