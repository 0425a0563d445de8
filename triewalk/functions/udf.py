"""User functions for SQL: the meet of two sorted arrays, grouped kernels, and rules as table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult

from ..kernel.meet import meet_arrays
from ..kernel.walk import ColumnTrie, walk_batches
from ..plans.ir import Atom, JoinQuery, QueryError
from ..plans.parse import rule


@F.pandas_udf(T.ArrayType(T.LongType()))
def meet_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Common values of two sorted arrays of longs, batch by batch."""
    return pd.Series([meet_arrays([np.asarray(x), np.asarray(y)]) if x is not None and y is not None else None for x, y in zip(a, b, strict=True)])


@F.pandas_udf(T.LongType())
def meet_size_udaf(keys: pd.Series, tags: pd.Series) -> int:
    """Aggregate: how many distinct keys occur under every tag of the group."""
    sets = [np.unique(keys[tags == t]) for t in sorted(tags.unique())]
    return int(len(meet_arrays(sets))) if sets else 0


def sorted_list(col) -> F.Column:
    """Aggregate: sorted distinct values as an array."""
    return F.sort_array(F.collect_set(col))


def small_triangles(edges: DataFrame, by: str) -> DataFrame:
    """Triangles of each group's small graph (columns by, u, v), a group in a task's memory."""

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        t = ColumnTrie.of([g["u"].to_numpy(), g["v"].to_numpy()])
        found = [np.stack(b, axis=1) for b in walk_batches([t, t, t], [[(0, 0), (2, 0)], [(0, 1), (1, 0)], [(1, 1), (2, 1)]])]
        rows = np.concatenate(found) if found else np.empty((0, 3), np.int64)
        return pd.DataFrame({by: key[0], "a": rows[:, 0], "b": rows[:, 1], "c": rows[:, 2]})

    kind = edges.schema[by].dataType.simpleString()
    return edges.groupBy(by).applyInPandas(run, f"{by} {kind}, a long, b long, c long")


def joined_groups(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """Binary join of two relations (key, x) and (key, y) by cogrouped kernels."""

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return a.merge(b, on=key)[[key, "x", "y"]]

    kind = left.schema[key].dataType.simpleString()
    return left.groupBy(key).cogroup(right.groupBy(key)).applyInPandas(run, f"{key} {kind}, x long, y long")


@F.udtf(returnType="a bigint, b bigint, c bigint")
class WalkTriangle:
    """Triangles of the rows (atom, x, y) of one partition: SELECT * FROM walk_triangle(TABLE(rows) PARTITION BY cell)."""

    def __init__(self):
        self.rows: list[list[tuple[int, int]]] = [[], [], []]

    def eval(self, row) -> None:
        self.rows[row["atom"]].append((row["x"], row["y"]))

    def terminate(self) -> Iterator[tuple]:
        if all(self.rows):
            tries = [ColumnTrie.of([np.array([x for x, _ in r]), np.array([y for _, y in r])]) for r in self.rows]
            for b in walk_batches(tries, [[(0, 0), (2, 0)], [(0, 1), (1, 0)], [(1, 1), (2, 1)]]):
                yield from zip(*(c.tolist() for c in b), strict=True)


@F.udtf
class WalkRule:
    """Answers of any rule of atoms over longs: SELECT * FROM walk_rule('Q(a,b,c) :- ...', TABLE(rows) PARTITION BY cell), rows as
    rule_rows makes them. A cell is walked in a task's memory."""

    @staticmethod
    def analyze(text: AnalyzeArgument, rows: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(T.StructType([T.StructField(v, T.LongType()) for v in rule(text.value).vars]))

    def __init__(self):
        self.text, self.rows = None, {}

    def eval(self, text: str, row) -> None:
        self.text = text
        self.rows.setdefault(row["atom"], []).append(tuple(row[f"x{i}"] for i in range(len(row) - 2)))

    def terminate(self) -> Iterator[tuple]:
        if self.text is not None:
            q = rule(self.text)
            columns = [[np.array([r[i] for r in self.rows.get(k, ())], dtype=np.int64) for i in range(len(a.terms))] for k, a in enumerate(q.body)]
            for b in walk_rule_arrays(q, columns):
                yield from zip(*(c.tolist() for c in b), strict=True)


def walk_rule_arrays(q: JoinQuery, columns: list[list[np.ndarray]]) -> Iterator[list[np.ndarray]]:
    """Bindings of all variables of a rule of atoms without constants, as blocks; columns: those of each atom's rows."""
    order = list(q.vars)
    if any(not isinstance(a, Atom) or len(set(a.terms)) < len(a.terms) or len(a.vars) < len(a.terms) for a in q.body):
        raise QueryError("atoms of different variables only")
    vs = [sorted(a.terms, key=order.index) for a in q.body]
    tries = [ColumnTrie.of([c[a.terms.index(v)] for v in names]) for a, names, c in zip(q.body, vs, columns, strict=True)]
    yield from walk_batches(tries, [[(i, names.index(v)) for i, names in enumerate(vs) if v in names] for v in order])


def rule_rows(text: str, relations: dict[str, DataFrame], cells: int) -> DataFrame:
    """(cell, atom, x0, x1, ...) of the atoms of a rule, dealt to cells by a hash of its first variable; atoms without it go to all."""
    q = rule(text)
    first, width, out = q.vars[0], max(len(a.terms) for a in q.body), None
    for k, a in enumerate(q.body):
        df = relations[a.relation].toDF(*(f"x{i}" for i in range(len(a.terms)))).dropna()
        key = F.pmod(F.xxhash64(F.col(f"x{a.terms.index(first)}")), F.lit(cells)) if first in a.terms else F.explode(F.sequence(F.lit(0).cast("long"), F.lit(cells - 1).cast("long")))
        part = df.select(key.alias("_cell"), "*").select(F.col("_cell").cast("int").alias("cell"), F.lit(k).alias("atom"), *(F.col(f"x{i}").cast("long") if i < len(a.terms) else F.lit(0).cast("long").alias(f"x{i}") for i in range(width)))
        out = part if out is None else out.unionByName(part)
    return out


def register(spark: SparkSession) -> None:
    spark.udf.register("meet_arrays", meet_udf)
    spark.udtf.register("walk_triangle", WalkTriangle)
    spark.udtf.register("walk_rule", WalkRule)
