"""Components of graphs whose links are rows, and chains by doubling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import store


def components(edges: DataFrame) -> DataFrame:
    """(a, b) -> (node, component): the smallest node reachable, for each node that has a link to another.

    Alternates two rewritings of the links to stars until nothing changes: greater neighbours are hung
    below the smallest of a neighbourhood, then lesser ones. Minima are aggregated before the join, so
    a node with very many links isn't gathered anywhere.
    """
    now = store(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links")
    mark = None
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        lower = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(lower, "a")
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(small.select("a", F.col("m").alias("b")))
        now = store(small.where("a <> b").distinct(), "links")
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if seen == mark:
            break
        mark = seen
    stars = now.groupBy("a").agg(F.min("b").alias("component"))
    return stars.select(F.col("a").alias("node"), "component").unionByName(stars.select(F.col("component").alias("node"), "component").distinct())


def pointer_double(links: DataFrame, seeds: DataFrame, rounds: int) -> DataFrame:
    """Links (a, b, value), seeds (track, node) -> (track, node, value): all nodes less than 2 ** rounds links from a seed.

    `value` is that of the link that leads to the node, null for the seed. Jumps double in length, one row for each
    node; only what seeds reach is kept on the way.
    """
    reach, jump = seeds.select("track", "node", F.lit(None).cast(links.schema["value"].dataType).alias("value")), links.select("a", "b", "value")
    for k in range(rounds):
        more = reach.select("track", F.col("node").alias("a")).join(jump, "a").select("track", F.col("b").alias("node"), "value")
        reach = store(reach.unionByName(more), "reach")
        if k < rounds - 1:
            far = jump.select(F.col("a").alias("b"), F.col("b").alias("far"), F.col("value").alias("last"))
            jump = store(jump.select("a", "b").join(far, "b").select("a", F.col("far").alias("b"), F.col("last").alias("value")), "jump")
    return reach
