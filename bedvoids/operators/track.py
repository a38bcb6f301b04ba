"""Matching bubbles of consecutive steps by the voxels they share, and following them."""

from __future__ import annotations

from math import ceil, log2

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import scalar
from ..sources.shared import store
from .graph import components, pointer_double


def overlaps(labels: DataFrame, gap: int = 1, engine: str = "join") -> DataFrame:
    """step, src, dst, inter, size_a, size_b: bubbles of a step and of the one `gap` later that share voxels.

    All steps in one job. "window" needs one shuffle and no join, since a voxel has one bubble a step.
    """
    at = labels.select("step", "voxel", "bubble")
    if engine == "window":
        w = Window.partitionBy("voxel").orderBy("step")
        if gap != 1:
            w = Window.partitionBy("voxel", F.pmod(F.col("step"), F.lit(gap))).orderBy("step")
        pairs = at.select(F.lag("step").over(w).alias("before"), F.lag("bubble").over(w).alias("src"), "step", F.col("bubble").alias("dst")).where(F.col("step") - F.col("before") == gap).select(F.col("before").alias("step"), "src", "dst")
    else:
        later = at.select((F.col("step") - gap).alias("step"), "voxel", F.col("bubble").alias("dst"))
        pairs = at.withColumnRenamed("bubble", "src").join(later, ["step", "voxel"]).select("step", "src", "dst")
    shared = pairs.groupBy("step", "src", "dst").agg(F.count(F.lit(1)).alias("inter"))
    size = at.groupBy("step", "bubble").agg(F.count(F.lit(1)).alias("size"))
    a = size.select("step", F.col("bubble").alias("src"), F.col("size").alias("size_a"))
    b = size.select((F.col("step") - gap).alias("step"), F.col("bubble").alias("dst"), F.col("size").alias("size_b"))
    return shared.join(a, ["step", "src"]).join(b, ["step", "dst"]).select("step", "src", "dst", "inter", "size_a", "size_b")


def measured(edges: DataFrame) -> DataFrame:
    """Adds dice, jaccard and the overlap coefficient."""
    c = [F.col(x) for x in ("inter", "size_a", "size_b")]
    return edges.select("*", scalar.dice(*c).alias("dice"), scalar.jaccard(*c).alias("jaccard"), scalar.overlap_coefficient(*c).alias("overlap"))


def best_links(edges: DataFrame, direction: str = "forward") -> DataFrame:
    """step, src, dst, inter, dice: for each bubble its best partner after it (forward) or before it (backward)."""
    own, other = ("src", "dst") if direction == "forward" else ("dst", "src")
    w = Window.partitionBy("step", own).orderBy(F.desc("dice"), F.desc("inter"), F.asc(other))
    found = edges if "dice" in edges.columns else measured(edges)
    return found.withColumn("_r", F.row_number().over(w)).where("_r = 1").select("step", "src", "dst", "inter", "dice")


def _node(step: str | Column, bubble: str) -> Column:
    """A step and a bubble as one number."""
    return (F.col(step) if isinstance(step, str) else step).cast("long") * F.lit(1 << 32) + F.col(bubble)


def _steps(edges: DataFrame) -> int:
    row = edges.agg(F.min("step"), F.max("step")).first()
    return 0 if row[0] is None else row[1] - row[0] + 1


def trace_all(edges: DataFrame, step: int, bubble: int | None = None, bubbles: DataFrame | None = None, gap: int = 1) -> DataFrame:
    """track, step, bubble, dice of every bubble of a step (or the one given), both ways until nothing overlaps.

    A track is named by its seed. Chains of best links are followed by doubling: a number of joins that is
    the logarithm of the number of steps, for all seeds at once. Dice belongs to the link towards the seed.
    """
    seeds = bubbles.where(F.col("step") == step).select("step", "bubble").distinct() if bubbles is not None else edges.where(F.col("step") == step).select("step", F.col("src").alias("bubble")).unionByName(edges.where(F.col("step") == step - gap).select(F.lit(step).alias("step"), F.col("dst").alias("bubble"))).distinct()
    if bubble is not None:
        seeds = seeds.where(F.col("bubble") == bubble)
    rounds = max(1, ceil(log2(_steps(edges) + 2)))
    start = seeds.select(F.col("bubble").cast("long").alias("track"), _node("step", "bubble").alias("node"))
    parts = []
    for direction, own, other in (("forward", "src", "dst"), ("backward", "dst", "src")):
        at, to = (F.col("step"), F.col("step") + gap) if direction == "forward" else (F.col("step") + gap, F.col("step"))
        links = store(best_links(edges, direction).select(_node(at, own).alias("a"), _node(to, other).alias("b"), F.col("dice").alias("value")), "best")
        found = pointer_double(links, start, rounds).select("track", F.shiftright("node", 32).cast("int").alias("step"), F.pmod("node", F.lit(1 << 32)).cast("int").alias("bubble"), F.col("value").alias("dice"))
        parts.append(found if direction == "forward" else found.where(F.col("step") < step))
    return parts[0].unionByName(parts[1])


def trace(edges: DataFrame, step: int, bubble: int, gap: int = 1) -> DataFrame:
    return trace_all(edges, step, bubble, gap=gap)


def trace_recursive(edges: DataFrame, step: int, bubble: int, gap: int = 1) -> DataFrame:
    """The same for one seed as a recursive query: one level for each step."""
    spark = edges.sparkSession
    for d in ("forward", "backward"):
        store(best_links(edges, d), "best").createOrReplaceTempView(f"_best_{d}")
    return spark.sql(f"""
        WITH RECURSIVE ahead(step, bubble, dice) AS (
            SELECT CAST({step} AS INT), CAST({bubble} AS INT), CAST(NULL AS DOUBLE)
            UNION ALL SELECT CAST(l.step + {gap} AS INT), CAST(l.dst AS INT), l.dice FROM ahead a JOIN _best_forward l ON l.step = a.step AND l.src = a.bubble
        ), back(step, bubble, dice) AS (
            SELECT CAST({step} AS INT), CAST({bubble} AS INT), CAST(NULL AS DOUBLE)
            UNION ALL SELECT CAST(l.step AS INT), CAST(l.src AS INT), l.dice FROM back a JOIN _best_backward l ON l.step = a.step - {gap} AND l.dst = a.bubble
        )
        SELECT CAST({bubble} AS BIGINT) AS track, step, bubble, dice FROM ahead
        UNION ALL SELECT CAST({bubble} AS BIGINT), step, bubble, dice FROM back WHERE step < {step}""")


def all_tracks(edges: DataFrame, bubbles: DataFrame, gap: int = 1) -> DataFrame:
    """track, step, bubble, dice of the whole run: chains of links that are best both ways; every bubble is in one."""
    mutual = best_links(edges, "forward").join(best_links(edges, "backward").select("step", "src", "dst"), ["step", "src", "dst"])
    links = store(mutual.select(_node("step", "src").alias("a"), _node(F.col("step") + gap, "dst").alias("b"), "dice"), "mutual")
    found = components(links.select("a", "b"))
    nodes = bubbles.select("step", "bubble").distinct().withColumn("node", _node("step", "bubble"))
    named = nodes.join(found, "node", "left").join(links.select(F.col("b").alias("node"), "dice"), "node", "left")
    return named.select(F.coalesce("component", "node").alias("track"), "step", "bubble", "dice")


def with_traits(tracks: DataFrame, traits: DataFrame) -> DataFrame:
    return tracks.join(traits, ["step", "bubble"])


def rise_velocity(track: DataFrame, dt: float = 1.0) -> DataFrame:
    """Adds rise_velocity: way of the centroid along x since the step before, by time."""
    w = Window.partitionBy("track").orderBy("step")
    return track.withColumn("rise_velocity", (F.col("xc") - F.lag("xc").over(w)) / ((F.col("step") - F.lag("step").over(w)) * F.lit(float(dt))))


def flag_low_confidence(track: DataFrame, floor: float = 0.3, k: float = 2.0, last: int = 5) -> DataFrame:
    """Adds low_confidence: Dice below the floor, or abruptly below the mean of the links before."""
    w = Window.partitionBy("track").orderBy("step").rowsBetween(-last, -1)
    mean, spread, n = F.avg("dice").over(w), F.stddev_pop("dice").over(w), F.count("dice").over(w)
    low = (F.col("dice") < floor) | ((n >= 2) & (F.col("dice") < F.round(mean - F.lit(k) * spread, 12) - F.lit(1e-9)))
    return track.withColumn("low_confidence", F.coalesce(low, F.lit(False)))
