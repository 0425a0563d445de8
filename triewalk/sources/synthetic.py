"""Instances made by rule: grids, the projection family, the density example; of ranges, or of the keys of a given table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import cut


def product(spark: SparkSession, m: int, n: int) -> DataFrame:
    """[0, m) x [0, n) as columns a, b."""
    return spark.range(m * n).select(F.expr(f"id div {n}").alias("a"), F.expr(f"id % {n}").alias("b"))


def grid(spark: SparkSession, m: int) -> DataFrame:
    return product(spark, m, m)


def projection_instance(spark: SparkSession, j: int) -> dict[str, DataFrame]:
    """R, S, T for n = 2^(8j): R of n^(3/8) by n^(5/8), S turned round, T of n by 1."""
    n = 1 << (8 * j)
    few, many = 1 << (3 * j), 1 << (5 * j)
    return {"R": product(spark, few, many), "S": product(spark, many, few), "T": product(spark, n, 1)}


def residues(df: DataFrame, key: str, n: int) -> DataFrame:
    """The different values of a key modulo n, as x, written out."""
    return cut(df.select(F.pmod(F.col(key), F.lit(n)).cast("long").alias("x")).distinct(), "residues")


def grid_of(df: DataFrame, key: str, m: int) -> DataFrame:
    """All pairs of the values of a key modulo m."""
    x = residues(df, key, m)
    return x.toDF("a").crossJoin(x.toDF("b"))


def projection_of(lines: DataFrame, j: int) -> dict[str, DataFrame]:
    """The projection instance for n = 2^(8j) of the suppliers and parts of all lines, modulo n^(3/8) and n^(5/8); T numbers R's rows."""
    few, many = 1 << (3 * j), 1 << (5 * j)
    r = residues(lines, "l_suppkey", few).toDF("a").crossJoin(residues(lines, "l_partkey", many).toDF("b"))
    return {"R": r, "S": r.select(F.col("b").alias("a"), F.col("a").alias("b")), "T": r.select((F.col("a") * many + F.col("b")).alias("a"), F.lit(0).cast("long").alias("b"))}


def hub(spark: SparkSession, n: int) -> DataFrame:
    """A graph of n spokes, each joined to 0 both ways, and a path along them: few triangles, and n^2 pairs of edges that meet in 0."""
    return hub_of(spark.range(1, n + 1).toDF("i"))


def hub_of(spokes: DataFrame) -> DataFrame:
    """The hub graph of given spokes (i, from 1); the path joins those that follow each other."""
    path = spokes.toDF("u").join(spokes.toDF("v"), F.col("v") == F.col("u") + 1)
    return spokes.selectExpr("0L as u", "i as v").union(spokes.selectExpr("i as u", "0L as v")).union(path)


def density_instance(spark: SparkSession, n: int) -> list[DataFrame]:
    """Three key sets of 2n of which any two share n and all three none."""
    r = lambda a, z: spark.range(a, z).withColumnRenamed("id", "x")
    return [r(0, 2 * n), r(n, 3 * n), r(0, n).union(r(2 * n, 3 * n))]
