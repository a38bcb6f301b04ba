"""Particles that arrive while a simulation runs."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.grid import GridSpec, Target
from ..operators import density
from ..plans.pipeline import in_situ
from ..sources.fields import write_fields

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Event files as a stream; `ts` becomes a timestamp, since watermarks need one."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def producer(spark: SparkSession, rows_per_second: int, grid: GridSpec) -> DataFrame:
    """A coupled producer to try a pipeline with: particles that arrive at a rate, all over the bed, a step a second."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    place = [(F.lit(lo) + F.pmod(F.xxhash64("value", F.lit(i)), F.lit(1 << 20)) / F.lit(float(1 << 20)) * F.lit(hi - lo)).alias(a) for i, (a, lo, hi) in enumerate(zip("xyz", grid.lo, grid.hi, strict=True))]
    return rows.select(F.col("timestamp").alias("ts"), F.floor(F.col("value") / rows_per_second).cast("int").alias("step"), *place, F.lit(1.0).alias("vx"), F.lit(0.0).alias("vy"), F.lit(0.0).alias("vz"))


def event_windows(stream: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "6 hours", gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """Counts and means by tumbling, sliding or session windows; a window is final when the watermark has passed it."""
    timed = stream.withWatermark("ts", late)
    if kind == "tumbling":
        keys = [F.window("ts", size).alias("w")]
    elif kind == "sliding":
        keys = [F.window("ts", size, slide).alias("w")]
    elif kind == "session":
        keys = [F.session_window("ts", gap).alias("w"), F.col("user_id")]
    else:
        raise ValueError(kind)
    rest = ["user_id"] if kind == "session" else []
    return timed.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *rest, "n", "total")


def histogram_stream(particles: DataFrame, grid: GridSpec, step_seconds: int = 86400, late: str = "1 day") -> DataFrame:
    """The histogram of a stream of particles with event time `ts`: a step is a period, final once the watermark passed it."""
    binned = particles.withWatermark("ts", late).where(grid.inside()).select("ts", "vx", *[c.alias(k) for k, c in grid.bins().items()])
    out = binned.groupBy(F.window("ts", f"{step_seconds} seconds").alias("w"), "ix", "iy", "iz").agg(F.count(F.lit(1)).alias("n"), F.sum("vx").alias("sum_vx"))
    return out.select((F.col("w.start").cast("long") / step_seconds).cast("int").alias("step"), "ix", "iy", "iz", "n", "sum_vx")


def once_each(stream: DataFrame, key: str = "event_id", late: str = "1 day") -> DataFrame:
    """Particles that are sent again count once."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def with_material(stream: DataFrame, materials: DataFrame, on: str) -> DataFrame:
    """A stream with a static dimension table."""
    return stream.join(materials, on, "left")


def with_velocities(positions: DataFrame, velocities: DataFrame, key: str = "event_id", within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Two streams of one particle set, joined within a bound of time."""
    p, v = positions.withWatermark("ts", late).alias("p"), velocities.withWatermark("ts", late).alias("v")
    return p.join(v, F.expr(f"p.{key} = v.{key} AND v.ts BETWEEN p.ts AND p.ts + INTERVAL {within}"))


def in_situ_stream(particles: DataFrame, grid: GridSpec, target: Target, path: str, checkpoint: str, **options) -> StreamingQuery:
    """Each micro-batch holds whole steps; its fields replace those steps on disk, so a restart leaves nothing double."""

    def step(batch: DataFrame, _: int) -> None:
        if not batch.isEmpty():
            write_fields(in_situ(batch, grid, target, **options).fields, path)

    return particles.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def finished(df: DataFrame, sink: str, checkpoint: str, mode: str = "append") -> StreamingQuery:
    """Runs a stream over all that is there into Parquet files."""
    return df.writeStream.format("parquet").option("path", sink).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()


def online_edges(labels: DataFrame) -> DataFrame:
    """step, src, dst, inter of arriving (step, voxel, bubble, tile): each tile keeps the voxels of the step before as state."""

    def follow(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = dict(zip(*state.get, strict=True)) if state.exists else {}
        step = held.pop(-1, None)
        for rows in sorted((g for p in parts for g in p.groupby("step")), key=lambda g: g[0]):
            now, part = int(rows[0]), rows[1]
            if step is not None and now < step:
                continue
            if step == now:
                held |= dict(zip(part["voxel"], part["bubble"], strict=True))
                continue
            if step == now - 1:
                pairs = [(held[v], b) for v, b in zip(part["voxel"], part["bubble"], strict=True) if v in held]
                if pairs:
                    n = pd.DataFrame(pairs, columns=["src", "dst"]).value_counts().reset_index(name="inter")
                    yield pd.DataFrame({"step": step, "src": n["src"].astype("int32"), "dst": n["dst"].astype("int32"), "inter": n["inter"].astype("int64")})
            held, step = dict(zip(part["voxel"], part["bubble"], strict=True)), now
        if step is not None:
            state.update(([-1, *map(int, held)], [step, *map(int, held.values())]))

    return labels.groupBy("tile").applyInPandasWithState(follow, "step int, src int, dst int, inter long", "voxels array<long>, bubbles array<long>", "append", GroupStateTimeout.NoTimeout)


def batches(particles: DataFrame, path: str, key: Callable | None = None) -> None:
    """Test help: a file for each step, oldest first."""
    for row in particles.select("step").distinct().orderBy("step").collect():
        particles.where(F.col("step") == row["step"]).coalesce(1).write.mode("append").parquet(path)
