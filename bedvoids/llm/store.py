"""What these operators share: tables kept where every executor sees them, and ranks over all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.graph import components
from ..sources.shared import discard, drop, fresh_path, scratch, store, table

__all__ = ["components", "discard", "drop", "fresh_path", "global_rank", "scratch", "store", "table"]


def global_rank(df: DataFrame, order: list[Column], within: str | None = None, name: str = "rank") -> DataFrame:
    """Adds `name`: the place from 1 of each row in the order, counted inside `within` if given.

    Rows are dealt by ranges of the whole order, so no group has to fit one task; only counts of each
    range are summed up across ranges. `order` has to begin with `within` and leave no ties that matter.
    """
    spark = df.sparkSession
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    at = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    at = store(at.withColumn("_part", F.shiftright("_at", 33)), "rank")
    keys = ["_part"] + ([within] if within else [])
    parts = at.groupBy(*keys).agg(F.min("_at").alias("_from"), F.count(F.lit(1)).alias("_n"))
    group = F.col(within) if within else F.lit(0)
    # a group has a row for each range it touches; the ranges of a group stand in a row of partitions
    if within:
        before = F.coalesce(F.sum("_n").over(Window.partitionBy(group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    else:
        before = F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = parts.withColumn("_before", before).select(F.col("_part").alias("_p"), *([F.col(within).alias("_w")] if within else []), "_from", "_before")
    on = F.col("_part") == F.col("_p")
    if within:
        on = on & F.col(within).eqNullSafe(F.col("_w"))
    out = at.join(offsets, on)
    return out.withColumn(name, F.col("_before") + F.col("_at") - F.col("_from") + 1).drop("_at", "_part", "_p", "_w", "_from", "_before")
