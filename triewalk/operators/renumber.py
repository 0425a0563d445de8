"""The proof's transform of an instance, as checks: renumbering a relation at a variable."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.rewrite import KeyFrame
from .domain import encode_domain
from .engine import Prepared, execute


def renumber(df: DataFrame, var: str, order: list[str]) -> DataFrame:
    """Siblings at var become 0, 1, ...; columns later in the order become 0; repeats go. Without var only the latter two happen."""
    cols = [v for v in order if v in df.columns]
    at = order.index(var)
    kept, later = [v for v in cols if order.index(v) < at], [v for v in cols if order.index(v) > at]
    zeros = [F.lit(0).cast("long").alias(v) for v in later]
    if var not in cols:
        return df.select(*kept, *zeros).distinct().select(*cols)
    if kept:
        rank = (F.dense_rank().over(Window.partitionBy(*kept).orderBy(var)) - 1).cast("long").alias(var)
        return df.select(*kept, var).distinct().select(*kept, rank, *zeros).select(*cols)
    return encode_domain([(df, var)]).select(F.col("code").alias(var), *zeros).select(*cols)


def witness(p: Prepared, order: list[str], var: str) -> DataFrame:
    """The query over the instance renumbered at var: it has as many answers as var's level cost."""
    frames = [KeyFrame(f.name, f.vars, renumber(f.df, var, order)) for f in p.frames]
    return execute(Prepared(p.head, frames, [], {v: "long" if order.index(v) >= order.index(var) else t for v, t in p.types.items()}, p.relations), "levels", order)


def size_shrinks(df: DataFrame, var: str, order: list[str]) -> bool:
    return renumber(df, var, order).count() <= df.distinct().count()


def projections_shrink(df: DataFrame, var: str, order: list[str]) -> bool:
    """Whether no projection has more rows after renumbering."""
    cols = df.columns
    sets = [[c for i, c in enumerate(cols) if m >> i & 1] for m in range(1, 1 << len(cols))]
    measure = lambda d: d.agg(*(F.count_distinct(*s).alias(f"p{i}") for i, s in enumerate(sets))).first()
    return all(b <= a for a, b in zip(measure(df), measure(renumber(df, var, order)), strict=True))
