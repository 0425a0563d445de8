"""Order-preserving dictionaries: values of any ordered type to longs and back, without a window over one partition."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.rewrite import KeyFrame
from ..sources.scratch import cut


def encode_domain(dfs: list[tuple[DataFrame, str]]) -> DataFrame:
    """(value, code): codes from 0 in the order of the distinct values of the given columns.

    Range partitions are in order; a value's code is its rank in its partition and the sizes of the partitions before, a row a partition.
    """
    values = None
    for df, c in dfs:
        one = df.select(F.col(c).alias("value")).where("value is not null")
        values = one if values is None else values.union(one)
    n = int(values.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = cut(values.distinct().repartitionByRange(n, "value").withColumn("part", F.spark_partition_id()), "domain")
    sizes = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy("value")) - 1
    return ranged.withColumn("rank", rank).join(F.broadcast(before), "part").select("value", (F.col("base") + F.col("rank")).cast("long").alias("code"))


def encode_frames(frames: list[KeyFrame]) -> tuple[list[KeyFrame], dict[str, DataFrame]]:
    """The frames with codes for values, and the dictionary of each variable."""
    names = list(dict.fromkeys(v for f in frames for v in f.vars))
    books = {v: cut(encode_domain([(f.df, v) for f in frames if v in f.vars]), "dictionary") for v in names}
    out = []
    for f in frames:
        df = f.df
        for v in f.vars:
            df = df.join(books[v].select(F.col("value").alias(v), F.col("code").alias(f"_{v}")), v).drop(v).withColumnRenamed(f"_{v}", v)
        out.append(KeyFrame(f.name, f.vars, df.select(*f.vars)))
    return out, books


def decode(df: DataFrame, books: dict[str, DataFrame]) -> DataFrame:
    columns = df.columns
    for v in columns:
        if v in books:
            df = df.join(books[v].select(F.col("code").alias(v), F.col("value").alias(f"_{v}")), v).drop(v).withColumnRenamed(f"_{v}", v)
    return df.select(*columns)
