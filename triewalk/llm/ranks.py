"""Positions in a total order without an unbounded window: rows are dealt to buckets, each bucket is ordered by itself,
and the small table of bucket totals gives where each bucket begins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Rows of a small table that may be sent to all executors.
BROADCAST_ROWS = 1 << 21


def sent_if_small(df: DataFrame, rows: int) -> DataFrame:
    """df, to be broadcast if its known number of rows allows; else the join is left to the planner."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def running_start(df: DataFrame, group: list[str], bucket: Column, order: list[Column], amount: Column, buckets: int, out: str, groups: int) -> DataFrame:
    """df with `out`: the sum of amount over the rows before this one, in its group, by (bucket, order).

    groups: how many groups there are; the table of totals, groups times `buckets` rows, is broadcast if that is few.
    order must be total within a bucket but for rows that are the same; bucket must be an int in [0, buckets).
    """
    keyed = df.withColumn("_bucket", bucket.cast("int")).withColumn("_amount", amount.cast("long"))
    totals = keyed.groupBy(*group, "_bucket").agg(F.sum("_amount").alias("_total"))
    before = Window.partitionBy(*group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = totals.select(*group, "_bucket", F.coalesce(F.sum("_total").over(before), F.lit(0)).alias("_start"))
    inside = Window.partitionBy(*group, "_bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    placed = keyed.withColumn("_inside", F.coalesce(F.sum("_amount").over(inside), F.lit(0)))
    right = starts.select(*(F.col(g).alias(f"_g{i}") for i, g in enumerate(group)), F.col("_bucket").alias("_b"), "_start")
    same = F.col("_bucket") == F.col("_b")
    for i, g in enumerate(group):
        same = same & F.col(g).eqNullSafe(F.col(f"_g{i}"))
    return placed.join(sent_if_small(right, groups * buckets), same, "left").withColumn(out, F.col("_start") + F.col("_inside")).drop("_bucket", "_amount", "_inside", "_start", "_b", *(f"_g{i}" for i in range(len(group))))
