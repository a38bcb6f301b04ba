"""Events in the life of bubbles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RISE, DROP = 0.5, 0.33


def volume_events(track: DataFrame, rise: float = RISE, drop: float = DROP) -> DataFrame:
    """Adds change (of volume, relative) and event: merge on a sudden rise, split on a sudden drop."""
    w = Window.partitionBy("track").orderBy("step")
    change = F.col("volume") / F.lag("volume").over(w) - F.lit(1.0)
    out = track.withColumn("change", F.round(change, 9))
    return out.withColumn("event", F.when(F.col("change") >= rise, "merge").when(F.col("change") <= -drop, "split"))


def graph_events(edges: DataFrame, gap: int = 1) -> DataFrame:
    """step, bubble, event, degree: bubbles with several bubbles before them (merge), or after them (split; at the step after)."""
    merges = edges.groupBy("step", "dst").agg(F.count(F.lit(1)).alias("degree")).where("degree > 1")
    splits = edges.groupBy("step", "src").agg(F.count(F.lit(1)).alias("degree")).where("degree > 1")
    return merges.select((F.col("step") + gap).alias("step"), F.col("dst").alias("bubble"), F.lit("merge").alias("event"), "degree").unionByName(splits.select((F.col("step") + gap).alias("step"), F.col("src").alias("bubble"), F.lit("split").alias("event"), "degree"))


def births_deaths(edges: DataFrame, traits: DataFrame, gap: int = 1, burst_layer: int | None = None) -> DataFrame:
    """step, bubble, event: birth (none before it), dissipation (none after it), or burst if it then touches `burst_layer` or above.

    Bubbles of the first step aren't born then, and those of the last don't end there.
    """
    at = traits.select("step", "bubble", "ix_max")
    ends = traits.agg(F.min("step").alias("_lo"), F.max("step").alias("_hi"))
    before = edges.select((F.col("step") + gap).alias("step"), F.col("dst").alias("bubble"))
    after = edges.select("step", F.col("src").alias("bubble"))
    born = at.join(before, ["step", "bubble"], "left_anti").crossJoin(F.broadcast(ends)).where("step > _lo")  # one row
    died = at.join(after, ["step", "bubble"], "left_anti").crossJoin(F.broadcast(ends)).where("step < _hi")
    end = F.when(F.col("ix_max") >= burst_layer, "burst").otherwise("dissipation") if burst_layer is not None else F.lit("dissipation")
    return born.select("step", "bubble", F.lit("birth").alias("event")).unionByName(died.select("step", "bubble", end.alias("event")))


def event_counts(events: DataFrame) -> DataFrame:
    return events.where("event is not null").groupBy("event").agg(F.count(F.lit(1)).alias("n"))


def summary(tracks: DataFrame) -> DataFrame:
    """A row for each track: life, length of its way, greatest volume and where it had it."""
    w = Window.partitionBy("track").orderBy("step")
    step = tracks.withColumn("_way", F.abs(F.col("xc") - F.lag("xc").over(w)))
    return step.groupBy("track").agg(F.min("step").alias("first_step"), F.max("step").alias("last_step"), (F.max("step") - F.min("step") + 1).alias("lifetime"), F.coalesce(F.sum("_way"), F.lit(0.0)).alias("path_length"), F.max("volume").alias("max_volume"), F.max_by("step", F.struct("volume", -F.col("step"))).alias("max_volume_step"))
