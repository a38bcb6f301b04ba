"""Cost and accuracy."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.shared import bytes_of


def seconds(df: DataFrame) -> float:
    """Wall clock of computing all rows, without keeping them."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def stage_times(spark: SparkSession, stages: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """stage, seconds: each computed and kept for the next, timed apart."""
    return spark.createDataFrame([(k, seconds(f())) for k, f in stages.items()], "stage string, seconds double")


def share(stages: DataFrame, base_seconds: float) -> DataFrame:
    return stages.agg(F.sum("seconds").alias("seconds")).withColumn("share_of_base", F.col("seconds") / F.lit(float(base_seconds)))


def io_times(spark: SparkSession, outputs: dict[str, DataFrame], path: str) -> DataFrame:
    """kind, seconds, bytes of writing each output."""
    rows = []
    for k, df in outputs.items():
        t = time.perf_counter()
        df.write.mode("overwrite").parquet(f"{path}/{k}")
        rows.append((k, time.perf_counter() - t, bytes_of(spark, f"{path}/{k}")))
    return spark.createDataFrame(rows, "kind string, seconds double, bytes long")


def storage(spark: SparkSession, raw_path: str, field_path: str, particles: int, steps: int, stride: int = 10, checkpoint_every: int = 50) -> DataFrame:
    """What a run stores: all raw steps, raw at the stride, checkpoints, and fields at the stride."""
    raw, field = bytes_of(spark, raw_path), bytes_of(spark, field_path)
    per_step = raw / max(steps, 1)
    rows = [("raw, every step", raw), ("raw at the stride", int(per_step * -(-steps // stride))), ("checkpoints", int(per_step * -(-steps // checkpoint_every))), ("fields at the stride", field)]
    return spark.createDataFrame([(k, b, raw / max(particles, 1), b / max(raw, 1)) for k, b in rows], "kind string, bytes long, bytes_per_particle double, share_of_raw double")


def distance_count(report: DataFrame) -> DataFrame:
    return report.groupBy("step").agg(F.sum("distances").alias("distances"), F.max("iteration").alias("iterations"))


def homogeneity(labels: DataFrame, field: DataFrame) -> DataFrame:
    """step, within, total, ratio: variance inside clusters against all variance; from whole sums."""
    both = labels.select("step", "voxel", "cluster").join(field.select("step", "voxel", "density"), ["step", "voxel"])
    per = both.groupBy("step", "cluster").agg(F.count(F.lit(1)).alias("n"), F.sum("density").alias("s1"), F.sum(F.col("density") * F.col("density")).alias("s2"))
    within = F.sum(F.col("s2") - F.col("s1") * F.col("s1") / F.col("n")) / F.sum("n")
    total = F.sum("s2") / F.sum("n") - (F.sum("s1") / F.sum("n")) * (F.sum("s1") / F.sum("n"))
    return per.groupBy("step").agg(F.round(within, 6).alias("within"), F.round(total, 6).alias("total")).withColumn("ratio", F.round(F.col("within") / F.col("total"), 5))


def reconstruction_rmse(labels: DataFrame, field: DataFrame) -> DataFrame:
    """step, rmse: how far voxels lie from the mean of their cluster."""
    return homogeneity(labels, field).select("step", F.round(F.sqrt("within"), 5).alias("rmse"))


def dice_profile(edges: DataFrame) -> DataFrame:
    return edges.agg(F.count(F.lit(1)).alias("links"), F.min("dice").alias("lowest"), F.avg("dice").alias("mean"), F.percentile("dice", F.lit(0.5)).alias("median"), F.max("dice").alias("highest"))


def linked_dice(best: DataFrame, traits: DataFrame, gap: int = 1) -> DataFrame:
    """bubbles, linked, mean: best Dice of every bubble that has a step after it, 0 where nothing overlaps."""
    last = traits.agg(F.max("step").alias("_last"))
    own = traits.select("step", F.col("bubble").alias("src")).crossJoin(F.broadcast(last)).where(F.col("step") + gap <= F.col("_last"))  # one row
    both = own.join(best.select("step", "src", "dice"), ["step", "src"], "left")
    return both.agg(F.count(F.lit(1)).alias("bubbles"), F.count("dice").alias("linked"), F.avg(F.coalesce("dice", F.lit(0.0))).alias("mean"))


def sensitivity(traits: DataFrame, by: list[str]) -> DataFrame:
    """Number and volume of bubbles for every combination of parameters, and over all values of each."""
    return traits.cube(*by).agg(F.count(F.lit(1)).alias("bubbles"), F.sum("voxels").alias("voxels"))


def accuracy(found: DataFrame, truth: DataFrame) -> DataFrame:
    """step, hit, missed, extra, precision, recall, iou of voxels."""
    f = found.select("step", "voxel").distinct().withColumn("f", F.lit(1))
    t = truth.select("step", "voxel").distinct().withColumn("t", F.lit(1))
    n = f.join(t, ["step", "voxel"], "full").groupBy("step").agg(F.count_if(F.col("f").isNotNull() & F.col("t").isNotNull()).alias("hit"), F.count_if(F.col("f").isNull()).alias("missed"), F.count_if(F.col("t").isNull()).alias("extra"))
    ratio = lambda a, b: F.when(b > 0, a / b)
    h, m, e = F.col("hit"), F.col("missed"), F.col("extra")
    return n.select("*", ratio(h, h + e).alias("precision"), ratio(h, h + m).alias("recall"), ratio(h, h + m + e).alias("iou"))


def bubble_recall(found: DataFrame, truth_labels: DataFrame, least: float = 0.5) -> DataFrame:
    """step, bubble, voxels, covered, recalled: true bubbles of which enough voxels were found."""
    f = found.select("step", "voxel").distinct().withColumn("f", F.lit(1))
    n = truth_labels.join(f, ["step", "voxel"], "left").groupBy("step", "bubble").agg(F.count(F.lit(1)).alias("voxels"), F.count("f").alias("covered"))
    return n.withColumn("recalled", F.col("covered") >= F.col("voxels") * F.lit(least))


def tracking_accuracy(tracks: DataFrame, true_tracks: DataFrame, found_labels: DataFrame, true_labels: DataFrame) -> DataFrame:
    """true_track, steps, covered, switches: how often the found track behind a true one changes."""
    a = true_tracks.select(F.col("track").alias("true_track"), "step", "bubble").join(true_labels.select("step", "bubble", "voxel"), ["step", "bubble"]).drop("bubble")
    b = tracks.select("track", "step", "bubble").join(found_labels.select("step", "bubble", "voxel"), ["step", "bubble"]).drop("bubble")
    shared = a.join(b, ["step", "voxel"]).groupBy("true_track", "step", "track").agg(F.count(F.lit(1)).alias("n"))
    best = shared.groupBy("true_track", "step").agg(F.max_by("track", F.struct("n", -F.col("track"))).alias("track"))
    w = Window.partitionBy("true_track").orderBy("step")
    moved = best.withColumn("switch", F.coalesce(F.lag("track").over(w) != F.col("track"), F.lit(False)))
    life = true_tracks.groupBy(F.col("track").alias("true_track")).agg(F.countDistinct("step").alias("steps"))
    return life.join(moved.groupBy("true_track").agg(F.count(F.lit(1)).alias("covered"), F.count_if("switch").alias("switches")), "true_track", "left").na.fill(0)


def event_accuracy(found: DataFrame, planted: DataFrame) -> DataFrame:
    """event, hit, missed, extra by step."""
    f = found.where("event is not null").groupBy("step", "event").agg(F.count(F.lit(1)).alias("f"))
    t = planted.groupBy("step", "event").agg(F.count(F.lit(1)).alias("t"))
    n = f.join(t, ["step", "event"], "full").na.fill(0, ["f", "t"])
    return n.groupBy("event").agg(F.sum(F.least("f", "t")).alias("hit"), F.sum(F.greatest(F.col("t") - F.col("f"), F.lit(0))).alias("missed"), F.sum(F.greatest(F.col("f") - F.col("t"), F.lit(0))).alias("extra"))


def compactness(labels: DataFrame) -> DataFrame:
    """step, raw_values, distribution_values, ratio: voxels of a field against two numbers for each cluster."""
    n = labels.groupBy("step").agg(F.count(F.lit(1)).alias("raw_values"), (F.countDistinct("cluster") * 2).alias("distribution_values"))
    return n.withColumn("ratio", F.col("distribution_values") / F.col("raw_values"))
