"""What the walk is compared with: binary join trees, the heavy/light triangle, brute force, and plain SQL."""

from __future__ import annotations

import math
from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ir import Atom, Compare, Const, JoinQuery
from ..plans.rewrite import KeyFrame
from ..sources.scratch import cut


def _step(left: DataFrame, right: DataFrame) -> DataFrame:
    common = [c for c in right.columns if c in left.columns]
    return left.join(right, common) if common else left.crossJoin(right)


def semijoin_reduce(frames: list[KeyFrame]) -> list[KeyFrame]:
    """A pass forwards and one back: each frame keeps the rows that have partners in the frames beside it."""
    out = list(frames)
    for i, j in [*zip(range(1, len(out)), range(len(out) - 1), strict=True), *zip(range(len(out) - 2, -1, -1), range(len(out) - 1, 0, -1), strict=True)]:
        common = [v for v in out[i].vars if v in out[j].vars]
        if common:
            out[i] = KeyFrame(out[i].name, out[i].vars, out[i].df.join(out[j].df.select(*common).distinct(), common, "left_semi"))
    return out


def pairwise_frames(frames: list[KeyFrame], tree: list[int] | None = None, reduce: bool = False) -> DataFrame:
    """Binary joins in the given order of atoms (connected ones first by default)."""
    frames = semijoin_reduce(frames) if reduce else frames
    if tree is None:
        tree, rest = [0], list(range(1, len(frames)))
        while rest:
            seen = {v for i in tree for v in frames[i].vars}
            nxt = next((i for i in rest if seen & set(frames[i].vars)), rest[0])
            tree.append(nxt)
            rest.remove(nxt)
    out = frames[tree[0]].df
    for i in tree[1:]:
        out = _step(out, frames[i].df)
    return out


def intermediate_rows(frames: list[KeyFrame], tree: list[int]) -> list[int]:
    """Rows of each binary join of a tree but the last."""
    out, sizes = frames[tree[0]].df, []
    for i in tree[1:-1]:
        out = _step(out, frames[i].df)
        sizes.append(out.count())
    return sizes


def pairwise_all(frames: list[KeyFrame]) -> list[tuple[list[int], int]]:
    """Every left-deep tree (the first two unordered) with its largest intermediate, least first."""
    trees = [list(t) for t in permutations(range(len(frames))) if t[0] < t[1]]
    return sorted(((t, max(intermediate_rows(frames, t), default=0)) for t in trees), key=lambda x: (x[1], x[0]))


def heavy_values(r: DataFrame, b: str, tau: float) -> DataFrame:
    return r.groupBy(b).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > tau).select(b)


def heavy_light_parts(r: DataFrame, s: DataFrame, t: DataFrame, tau: float | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """R(a,b), S(b,c), T(a,c): the heavy values of b, their product with T, and the join of R's light rows with S."""
    tau = math.isqrt(r.count()) if tau is None else tau
    heavy = cut(heavy_values(r, "b", tau), "heavy")
    product = heavy.crossJoin(t)
    light = r.join(heavy, "b", "left_anti").join(s, "b")
    return heavy, product, light


def heavy_light(r: DataFrame, s: DataFrame, t: DataFrame, tau: float | None = None) -> DataFrame:
    """The triangle by heavy and light values of b (heavy: in more than tau rows of R); the two parts are disjoint."""
    _, product, light = heavy_light_parts(r, s, t, tau)
    high = product.join(s, ["b", "c"], "left_semi").join(r, ["a", "b"], "left_semi").select("a", "b", "c")
    return high.unionByName(light.join(t, ["a", "c"], "left_semi").select("a", "b", "c"))


def heavy_light_sweep(r: DataFrame, s: DataFrame, t: DataFrame, taus: list[float]) -> DataFrame:
    """tau, heavy values, rows of the product, rows of the light join; a row a threshold."""
    out = []
    for tau in taus:
        heavy, _, light = heavy_light_parts(r, s, t, tau)
        n = heavy.count()
        # a product's rows are known without making it
        out.append((float(tau), n, n * t.count(), light.count()))
    return r.sparkSession.createDataFrame(out, "tau double, heavy long, product_rows long, light_rows long")


def brute(frames: list[KeyFrame], order: list[str]) -> DataFrame:
    """Cross product and filter, for tiny inputs only: the ground truth."""
    out, seen = None, set()
    for i, f in enumerate(frames):
        df = f.df.select(*(F.col(v).alias(f"{v}__{i}") for v in f.vars))
        out = df if out is None else out.crossJoin(df)
        for v in f.vars:
            if v in seen:
                out = out.where(F.col(v) == F.col(f"{v}__{i}"))
            else:
                out, seen = out.withColumn(v, F.col(f"{v}__{i}")), seen | {v}
    return out.select(*order).distinct()


def pairwise_meet(dfs: list[DataFrame], key: str) -> DataFrame:
    """Intersection two at a time."""
    out = dfs[0].select(key).distinct()
    for d in dfs[1:]:
        out = out.join(d.select(key).distinct(), key, "left_semi")
    return out


def sort_merge(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Plain sort-merge join of two key sets."""
    return a.select(key).distinct().join(b.select(key).distinct().hint("merge"), key)


def to_sql(q: JoinQuery, columns: dict[str, list[str]]) -> str:
    """The same conjunction as SQL text; columns: names of each relation's columns."""
    from_, where, at = [], [], {}
    for i, p in enumerate(q.body):
        if isinstance(p, Compare):
            continue
        if not isinstance(p, Atom):
            raise TypeError("only conjunctions of atoms and comparisons")
        from_.append(f"{p.relation} t{i}")
        for c, t in zip(columns[p.relation], p.terms, strict=True):
            ref = f"t{i}.{c}"
            if isinstance(t, Const):
                where.append(f"{ref} = {t.value!r}")
            elif t in at:
                where.append(f"{ref} = {at[t]}")
            else:
                at[t] = ref
    for p in q.body:
        if isinstance(p, Compare):
            where.append(f"{at[p.left]} {p.op} {at[p.right] if isinstance(p.right, str) else p.right.value}")
    return f"SELECT DISTINCT {', '.join(f'{at[v]} AS {v}' for v in q.head)} FROM {', '.join(from_)}" + (f" WHERE {' AND '.join(where)}" if where else "")
