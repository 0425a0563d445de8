"""The given tables and the relations derived from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .scratch import cut


def load(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where=None) -> DataFrame:
    """A table, its columns pruned and its filter pushed to the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*cols) if cols else df


def load_text(spark: SparkSession, path: str, schema: str, fmt: str = "csv", **options) -> DataFrame:
    """CSV, JSON or text with a declared schema."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def save(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, mode: str = "errorifexists") -> None:
    w = df.write.format(fmt).mode(mode)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def next_in_order(df: DataFrame, order: list[str], value: str) -> DataFrame:
    """df with `next`: value (not null) of the row after this one in the order, without a window over all rows.

    Rows are dealt to ranges of the order of about equal size, however they crowd in time, and ordered within each; a range's last row takes
    the first value of the next range that has rows, from a table of a row a range.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = cut(df.repartitionByRange(n, *order).withColumn("_range", F.spark_partition_id()), "ordered")
    led = ranged.withColumn("_in", F.lead(value).over(Window.partitionBy("_range").orderBy(*order)))
    firsts = ranged.groupBy("_range").agg(F.min_by(value, F.struct(*order)).alias("_head"))
    heads = firsts.select("_range", F.lead("_head").over(Window.orderBy("_range")).alias("_next_head"))  # a row a range
    return led.join(F.broadcast(heads), "_range", "left").withColumn("next", F.coalesce("_in", "_next_head")).drop("_in", "_next_head", "_range")


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A derived relation by name; columns are positional."""
    t = lambda n, *c: load(spark, sf_dir, n, [*c])
    if name == "sn":
        return t("supplier", "s_suppkey", "s_nationkey")
    if name == "cn":
        return t("customer", "c_custkey", "c_nationkey")
    if name == "cs":
        return t("orders", "o_orderkey", "o_custkey").join(t("lineitem", "l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_suppkey").distinct()
    if name == "nn":
        cs = relation(spark, sf_dir, "cs")
        named = cs.join(relation(spark, sf_dir, "cn"), F.col("o_custkey") == F.col("c_custkey")).join(relation(spark, sf_dir, "sn"), F.col("l_suppkey") == F.col("s_suppkey"))
        return named.select(F.col("c_nationkey").cast("long").alias("a"), F.col("s_nationkey").cast("long").alias("b")).distinct()
    if name == "hop":
        e = next_in_order(t("events", "event_id", "ts", "user_id"), ["ts", "event_id"], "user_id")
        return e.where("next is not null and user_id != next").select(F.col("user_id").alias("u"), F.col("next").alias("v")).distinct()
    if name in ("co_supp", "co_part"):
        key = "l_suppkey" if name == "co_supp" else "l_partkey"
        a = t("lineitem", "l_orderkey", key).repartition("l_orderkey").distinct()  # dealt once: repeats and the join need no other exchange
        b = a.select(F.col("l_orderkey").alias("o2"), F.col(key).alias("k2"))
        return a.join(b, (F.col("l_orderkey") == F.col("o2")) & (F.col(key) < F.col("k2"))).select(F.col(key).alias("u"), F.col("k2").alias("v")).distinct()
    if name == "bts":
        return t("part", "p_brand", "p_type", "p_size").distinct()
    if name == "zipf":
        return t("lineitem", "l_partkey", "l_suppkey").select(F.expr("l_partkey % 400 * (l_partkey % 400) div 800").alias("u"), F.expr("2000 div (1 + l_suppkey * 7 % 200)").alias("v")).distinct()
    if name == "utd":
        return t("events", "user_id", "event_type", "ts").select("user_id", "event_type", F.dayofmonth("ts").alias("d")).distinct()
    raise KeyError(name)
