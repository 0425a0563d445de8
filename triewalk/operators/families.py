"""Families of instances: constraints on sizes, on projections, on graphs, and on the shape of tries."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.bounds import cover_bound, projection_bound
from ..sources.scratch import cut
from .renumber import renumber


@dataclass
class SizeFamily:
    """Instances whose relations have at most the given rows."""

    bounds: dict[str, int]

    def holds(self, instance: dict[str, DataFrame]) -> bool:
        return all(instance[n].distinct().count() <= b for n, b in self.bounds.items())

    def largest_answer(self, edges: dict[str, frozenset[str]]) -> float:
        """q: the most answers of any member, up to the bound's tightness."""
        return cover_bound(list(edges.values()), [self.bounds[n] for n in edges])[0]

    def largest_relation(self) -> int:
        """M."""
        return max(self.bounds.values())


@dataclass
class ProjectionFamily:
    """Instances whose projections have at most the given rows: (relation, columns) to bound."""

    bounds: dict[tuple[str, tuple[str, ...]], int]

    def holds(self, instance: dict[str, DataFrame]) -> bool:
        return all(instance[n].select(*cols).distinct().count() <= b for (n, cols), b in self.bounds.items())

    def largest_answer(self, edges: dict[str, frozenset[str]], sizes: dict[str, int]) -> float:
        small: dict[frozenset[str], int] = {}
        for (_, cols), b in self.bounds.items():
            small[frozenset(cols)] = min(b, small.get(frozenset(cols), b))
        return projection_bound(list(edges.values()), [sizes[n] for n in edges], small)


def graph_family(name: str, n: int) -> SizeFamily:
    """Graphs of at most n edges."""
    return SizeFamily({name: n})


def check_closure(family, instance: dict[str, DataFrame], order: list[str]) -> dict[str, bool]:
    """Whether the instance, a member, stays one when renumbered at each variable; columns are named by variables."""
    if not family.holds(instance):
        raise ValueError("the instance is not in the family")
    return {v: family.holds({n: renumber(df, v, order) for n, df in instance.items()}) for v in order}


def match_length(df: DataFrame, left: list[str], right: list[str], out: str = "match") -> DataFrame:
    """df with the length of the common prefix of two tuples of columns."""
    n, same = F.lit(0), F.lit(True)
    for a, b in zip(left, right, strict=True):
        same = same & F.col(a).eqNullSafe(F.col(b))
        n = n + F.when(same, 1).otherwise(0)
    return df.withColumn(out, n.cast("int"))


def degree_profile(df: DataFrame, first: str) -> DataFrame:
    """(rank, degree): degrees of the first column's values, largest first, ranks from 0, without a window over all rows."""
    degree = df.distinct().groupBy(F.col(first).alias("key")).agg(F.count(F.lit(1)).alias("degree"))
    # ranges of (degree, key), so that many keys of one degree fall into several; a key's rank is that in its range and the sizes before
    order = [F.col("degree").desc(), F.col("key")]
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = cut(degree.repartitionByRange(n, *order).withColumn("part", F.spark_partition_id()), "degrees")
    sizes = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("part", before.alias("start"))  # a row a range
    inside = F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1
    return ranged.withColumn("inside", inside).join(F.broadcast(starts), "part").select((F.col("start") + F.col("inside")).alias("rank"), "degree")


def dominance_violations(small: DataFrame, large: DataFrame, first: str) -> DataFrame:
    """Ranks at which small's degree is larger, or which large lacks; none means that small's trie embeds in large's."""
    a = degree_profile(small, first)
    b = degree_profile(large, first).select(F.col("rank").alias("r"), F.col("degree").alias("limit"))
    return a.join(b, F.col("rank") == F.col("r"), "left").where("limit is null or degree > limit").select("rank", "degree", "limit")


def _shape(rows: set[tuple]) -> tuple:
    by: dict = {}
    for r in rows:
        by.setdefault(r[0], set()).add(r[1:])
    return tuple(sorted((_shape(x) if next(iter(x)) else () for x in by.values()), key=repr))


def _fits(a: tuple, b: tuple) -> bool:
    """Whether the children of a can be matched to different children of b, each fitting in its partner."""
    partner: dict[int, int] = {}

    def place(i: int, seen: set[int]) -> bool:
        for j, child in enumerate(b):
            if j not in seen and _fits(a[i], child):
                seen.add(j)
                if j not in partner or place(partner[j], seen):
                    partner[j] = i
                    return True
        return False

    return len(a) <= len(b) and all(place(i, set()) for i in range(len(a)))


def shape_embeds(small: set[tuple], large: set[tuple]) -> bool:
    """Whether the trie of small is, up to names of values, part of the trie of large; for small inputs."""
    return not small or bool(large) and _fits(_shape(small), _shape(large))


@dataclass
class PrototypeFamily:
    """Instances whose tries embed in the prototypes'."""

    prototypes: dict[str, set[tuple]]

    def holds_rows(self, instance: dict[str, set[tuple]]) -> bool:
        return all(shape_embeds(rows, self.prototypes[n]) for n, rows in instance.items())

    def largest_relation(self) -> int:
        return max(len(p) for p in self.prototypes.values())
