"""The relational operators around the joins, each the Spark operator it names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ALGORITHMS = {"hash": "shuffle_hash", "merge": "merge", "broadcast": "broadcast"}


def filtered(df: DataFrame, *preds: Column) -> DataFrame:
    for p in preds:
        df = df.where(p)
    return df


def equi_join(a: DataFrame, b: DataFrame, on, how: str = "inner", algo: str | None = None) -> DataFrame:
    """algo: hash, merge or broadcast; none leaves it to the optimizer."""
    return a.join(b.hint(ALGORITHMS[algo]) if algo else b, on, how)


def theta_join(a: DataFrame, b: DataFrame, cond: Column) -> DataFrame:
    return a.join(b, cond)


def outer_join(a: DataFrame, b: DataFrame, on, how: str = "full") -> DataFrame:
    return a.join(b, on, how)


def semi(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_semi")


def anti(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_anti")


def range_join(points: DataFrame, spans: DataFrame, x: str, lo: str, hi: str, width: int, on: list[str] | None = None) -> DataFrame:
    """Pairs with lo <= x < hi (whole numbers): spans are put in every bucket of the given width that they touch, points in
    theirs, so the join is an equi-join on the bucket (and on `on`) with a filter."""
    p = points.withColumn("_bucket", F.floor(F.col(x) / width).cast("long"))
    s = spans.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(lo) / width).cast("long"), F.floor((F.col(hi) - 1) / width).cast("long"))))
    return p.join(s, ["_bucket", *(on or [])]).where((F.col(x) >= F.col(lo)) & (F.col(x) < F.col(hi))).drop("_bucket")


def asof_join(left: DataFrame, right: DataFrame, by: list[str], ts: str, tie: str, value: str, out: str) -> DataFrame:
    """left with the last non-null value of right at or before its time, in each group of `by`: one union and one window, no join."""
    cols = left.columns
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1))
    b = right.select(*(F.col(c) if c in [*by, ts, tie] else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(*by).orderBy(ts, "_side", tie).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn(out, F.last("_v", ignorenulls=True).over(w)).where("_side = 1").select(*cols, out)


def aggregate(df: DataFrame, keys: list[str], **aggs: Column) -> DataFrame:
    return df.groupBy(*keys).agg(*(c.alias(n) for n, c in aggs.items()))


def distinct_counts(df: DataFrame, sets: dict[str, list[str]], approx: bool = False) -> DataFrame:
    one = (lambda cols: F.approx_count_distinct(F.struct(*cols))) if approx else (lambda cols: F.count_distinct(*cols))
    return df.agg(*(one(cols).alias(n) for n, cols in sets.items()))


def grouping(df: DataFrame, keys: list[str], how: str, *aggs: Column) -> DataFrame:
    """how: cube or rollup, with grouping_id as level_id."""
    g = df.cube(*keys) if how == "cube" else df.rollup(*keys)
    return g.agg(F.grouping_id().cast("long").alias("level_id"), *aggs)


def ranked(df: DataFrame, keys: list[str], order: list[Column], out: str = "rank") -> DataFrame:
    return df.withColumn(out, F.row_number().over(Window.partitionBy(*keys).orderBy(*order)))


def framed(df: DataFrame, keys: list[str], order: list[Column], back: int, value: Column, out: str) -> DataFrame:
    return df.withColumn(out, value.over(Window.partitionBy(*keys).orderBy(*order).rowsBetween(-back, 0)))


def top_k(df: DataFrame, k: int, order: list[Column], by: list[str] | None = None) -> DataFrame:
    """The first k rows, of each group if `by` is given."""
    if not by:
        return df.orderBy(*order).limit(k)
    return ranked(df, by, order, "_rank").where(F.col("_rank") <= k).drop("_rank")


def set_op(a: DataFrame, b: DataFrame, op: str, all_: bool = False) -> DataFrame:
    name = {"union": "unionAll", "intersect": "intersectAll", "except": "exceptAll"}[op] if all_ else {"union": "union", "intersect": "intersect", "except": "subtract"}[op]
    out = getattr(a, name)(b)
    return out.distinct() if op == "union" and not all_ else out


def pivoted(df: DataFrame, keys: list[str], column: str, values: list, agg: Column) -> DataFrame:
    return df.groupBy(*keys).pivot(column, values).agg(agg)


def unpivoted(df: DataFrame, ids: list[str], values: list[str], name: str = "name", value: str = "value") -> DataFrame:
    return df.unpivot(ids, values, name, value)


def sampled(df: DataFrame, fraction: float, key: str, seed: int = 0) -> DataFrame:
    """Rows by a hash of their key: the same rows on every run and however the data are dealt."""
    return df.where(F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))
