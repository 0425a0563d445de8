"""The join one variable at a time over DataFrames.

A frame of prefixes is extended by the next variable. Of a prefix's slices the smallest is joined on, which makes exactly
the level cost in rows, and the other participants keep those that they hold by semi joins. `driver="global"` is the ablation:
one participant extends all prefixes of a level.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.choice import BROADCAST_ROWS
from ..plans.levels import Level, level_plan
from ..plans.rewrite import KeyFrame
from ..sources.scratch import cut

#: plain leaves the join algorithm to the optimizer.
HINTS = {"levels": "merge", "hash": "shuffle_hash", "plain": None}
#: Parts that a slice too large to be broadcast is dealt to when prefixes have nothing to join it by.
DEALT = 64


class Projections:
    """Projections of frames, each made once: atoms of one source share a table, and every level reads what is written out.

    about: estimated numbers of a frame's values of a variable, enough to tell the smaller of two; sizes are counted where there are none.
    """

    def __init__(self, frames: list[KeyFrame], about: dict[tuple[int, str], int] | None = None):
        self.frames, self.made, self.sizes, self.about = frames, {}, {}, about or {}

    def _names(self, at: int, cols: tuple[str, ...]) -> tuple[tuple, dict[str, str]]:
        """Key of a projection, and the stored name of each of its variables."""
        f = self.frames[at]
        names = {v: f.columns[f.vars.index(v)] if f.source else v for v in cols}
        return (f.source or at, tuple(sorted(names.values()))), names

    def of(self, at: int, cols: tuple[str, ...]) -> DataFrame:
        """Distinct values of some of a frame's variables."""
        if set(cols) == set(self.frames[at].vars):
            return self.frames[at].df.select(*cols)
        key, names = self._names(at, cols)
        if key not in self.made:
            renamed = self.frames[at].df.select(*(F.col(v).alias(names[v]) for v in sorted(cols, key=names.get)))
            self.made[key] = cut(renamed.distinct(), "projection")
        return self.made[key].select(*(F.col(f"`{names[v]}`").alias(v) for v in cols))

    def size(self, at: int, cols: tuple[str, ...]) -> int:
        f = self.frames[at]
        if set(cols) == set(f.vars) and f.rows is not None:
            return f.rows
        if len(cols) == 1 and (at, cols[0]) in self.about:
            return self.about[at, cols[0]]
        key, _ = self._names(at, cols)
        if key not in self.sizes:
            self.sizes[key] = self.of(at, cols).count()
        return self.sizes[key]

    def degrees(self, at: int, bound: tuple[str, ...], var: str, out: str) -> DataFrame:
        """How many values of var each binding of the bound variables has."""
        return self.of(at, (*bound, var)).groupBy(*bound).agg(F.count(F.lit(1)).alias(out))


def _hinted(df: DataFrame, hint: str | None) -> DataFrame:
    return df.hint(hint) if hint else df


def with_degrees(prefix: DataFrame, slices: Projections, level: Level, hint: str | None) -> DataFrame:
    """prefix with a column deg{k} for each participant; every prefix has a slice in each, by the levels before."""
    for k, p in enumerate(level.participants):
        bound = level.bound[k]
        if bound:
            prefix = prefix.join(_hinted(slices.degrees(p, bound, level.var, f"deg{k}"), hint), [*bound])
        else:
            prefix = prefix.withColumn(f"deg{k}", F.lit(slices.size(p, (level.var,))).cast("long"))
    return prefix


def first_level(slices: Projections, level: Level, hint: str | None, costs: list | None = None) -> DataFrame:
    """Values of the first variable: the smallest projection, cut down by the others."""
    sides = [(slices.of(p, (level.var,)), p) for p in level.participants]
    if len(sides) > 1 or costs is not None:
        sides.sort(key=lambda x: slices.size(x[1], (level.var,)))
        if costs is not None:
            costs.append(slices.size(sides[0][1], (level.var,)))
    (out, _), *rest = sides
    for other, _ in rest:
        out = out.join(_hinted(other, hint), level.var, "left_semi")
    return out


def product(prefix: DataFrame, values: DataFrame, n: int) -> DataFrame:
    """Every prefix with every value, which is what the level costs when no participant has a bound variable: the values go to all
    executors if they are few, else both sides are dealt out by a number that each prefix has all of."""
    if n <= BROADCAST_ROWS:
        return prefix.crossJoin(F.broadcast(values))
    dealt = values.withColumn("_part", F.pmod(F.xxhash64(*values.columns), F.lit(DEALT)))
    return prefix.withColumn("_part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(DEALT - 1).cast("long")))).join(dealt, "_part").drop("_part")


def extend(prefix: DataFrame, slices: Projections, level: Level, hint: str | None, driver: str = "per_prefix", costs: list | None = None) -> DataFrame:
    """The prefixes of the next level. costs, if given, gets the level cost."""
    cols = prefix.columns
    ways = len(level.participants)
    names = [f"deg{k}" for k in range(ways)]
    if ways > 1:
        # read once a branch, so it is written once; the prefix frame itself is read here only
        known = with_degrees(prefix, slices, level, hint)
        which = F.lit(ways - 1)
        for k in reversed(range(ways - 1)):
            which = F.when(F.col(names[k]) <= F.least(*(F.col(n) for n in names)), F.lit(k)).otherwise(which)
        known = cut(known.withColumn("_least", which), "level-degrees")
        if costs is not None:
            costs.append(known.agg(F.coalesce(F.sum(F.least(*names)), F.lit(0))).first()[0])
        if driver == "global":
            sums = known.agg(*(F.sum(n) for n in names)).first()
            branches = [(min(range(ways), key=lambda k: sums[k] or 0), known.select(*cols))]
        else:
            branches = [(k, known.where(F.col("_least") == k).select(*cols)) for k in range(ways)]
    else:
        if costs is not None:
            costs.append(with_degrees(prefix, slices, level, hint).agg(F.coalesce(F.sum("deg0"), F.lit(0))).first()[0])
        branches = [(0, prefix)]
    out = None
    for k, part in branches:
        bound = level.bound[k]
        slice_ = slices.of(level.participants[k], (*bound, level.var))
        grown = part.join(_hinted(slice_, hint), [*bound]) if bound else product(part, slice_, slices.size(level.participants[k], (level.var,)))
        for j, p in enumerate(level.participants):
            if j != k:
                on = [*level.bound[j], level.var]
                grown = grown.join(_hinted(slices.of(p, tuple(on)), hint), on, "left_semi")
        grown = grown.select(*cols, level.var)
        out = grown if out is None else out.unionByName(grown)
    return out


def run_levels(spark: SparkSession, frames: list[KeyFrame], order: list[str], engine: str = "levels", driver: str = "per_prefix", after=None, keep: list | None = None, costs: list | None = None, about: dict[tuple[int, str], int] | None = None) -> DataFrame:
    """All bindings. after(df, bound): filters to apply once variables are bound. keep: gets each level's prefix frame; costs: each level's cost."""
    hint = HINTS[engine]
    plan, slices = level_plan([f.vars for f in frames], order), Projections(frames, about)
    prefix = None
    for i, level in enumerate(plan):
        prefix = first_level(slices, level, hint, costs) if prefix is None else extend(prefix, slices, level, hint, driver, costs)
        if after:
            prefix = after(prefix, order[: i + 1])
        if keep is not None:
            prefix = cut(prefix, "level")
            keep.append(prefix)
    return prefix
