"""The facade: a rule and relations to a DataFrame of answers, by any of the engines."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.bounds import cover_bound
from ..plans.choice import acyclic, choose_engine, enough_cells
from ..plans.ir import And, Atom, Compare, Const, Exists, JoinQuery, Not, Or, QueryError, UnsafeVariable, analyze
from ..plans.levels import level_plan
from ..plans.order import choose_order, estimate_costs
from ..plans.parse import rule
from ..plans.rewrite import KeyFrame, key_frame, variable_types
from ..plans.stats import FrameStats, frame_stats
from ..sources.scratch import cut
from .broadcast_engine import TooLarge, run_broadcast
from .cell_engine import run_cells, whole_numbers
from .domain import decode, encode_frames
from .layout import LayoutCatalog
from .level_engine import Projections, run_levels

ENGINES = ("auto", "levels", "hash", "cells", "broadcast", "pairwise")
CELLS = 64


@dataclass
class Prepared:
    """A query lowered to a full conjunction of key frames, with what is to be filtered once variables are bound."""

    head: tuple[str, ...]
    frames: list[KeyFrame]
    filters: list
    types: dict
    relations: dict[str, DataFrame]

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys([*self.head, *(v for f in self.frames for v in f.vars)]))

    @property
    def edges(self) -> list[frozenset[str]]:
        return [frozenset(f.vars) for f in self.frames]


def _flat(parts) -> list:
    out = []
    for p in parts:
        out += _flat(p.parts) if isinstance(p, And) else [p]
    return out


def prepare(q: JoinQuery | str, relations: dict[str, DataFrame], order: list[str] | None = None, unique: tuple[str, ...] = ()) -> Prepared:
    """Analysis and lowering. Unions and inner existential parts become frames of their own; atoms joined by hidden variables
    become one frame over their visible variables, so what is left is a full conjunction over the head."""
    q = analyze(rule(q) if isinstance(q, str) else q, relations)
    types = variable_types(q, relations)
    order = order or list(q.vars)
    frames, filters = [], []
    for p in _flat(q.body):
        if isinstance(p, Atom):
            if not p.vars:
                raise QueryError("an atom of constants alone binds nothing")
            frames.append(key_frame(p, relations[p.relation], order, types, unique=p.relation in unique))
        elif isinstance(p, Or):
            vs = tuple(v for v in order if v in p.vars)
            arms = [run(JoinQuery(vs, _flat([a])), relations) for a in p.parts]
            df = arms[0]
            for a in arms[1:]:
                df = df.unionByName(a)
            frames.append(KeyFrame("or", vs, df.select(*(F.col(v).cast(types[v]).alias(v) for v in vs)).distinct()))
        elif isinstance(p, Exists):
            vs = tuple(v for v in order if v in p.vars)
            frames.append(KeyFrame("exists", vs, run(JoinQuery(vs, _flat([p.body])), relations)))
        else:
            filters.append(p)
    hidden = [v for v in q.vars if v not in q.head]
    if any(v in hidden for f in filters for v in f.vars):
        # filters over hidden variables need them bound: the whole is joined and projected
        inner = Prepared(tuple(q.vars), frames, filters, types, relations)
        done = execute(inner, "levels", order=list(inner.vars)).select(*q.head).distinct()
        return Prepared(q.head, [KeyFrame("projected", q.head, done)], [], types, relations)
    while hidden:
        group, new = [], {hidden[0]}
        while True:
            more = [f for f in frames if f not in group and new & set(f.vars)]
            if not more:
                break
            group += more
            new |= {v for f in more for v in f.vars if v in hidden}
        seen = tuple(v for v in q.head if any(v in f.vars for f in group))
        if len(group) == 1:
            df = group[0].df.select(*seen).distinct() if seen else group[0].df
        else:
            inner = Prepared((*seen, *new), group, [], types, relations)
            df = execute(inner, "levels", order=[*seen, *sorted(new)]).select(*seen).distinct()
        frames = [f for f in frames if f not in group]
        if seen:
            frames.append(KeyFrame("exists", seen, df))
        elif not df.limit(1).count():
            frames = [KeyFrame(f.name, f.vars, f.df.limit(0)) for f in frames]
        hidden = [v for v in hidden if v not in new]
    missing = [v for v in q.head if not any(v in f.vars for f in frames)]
    if missing:
        raise UnsafeVariable(str(missing))
    return Prepared(q.head, frames, filters, types, relations)


def _filter(p: Prepared):
    """after(df, bound): the filters whose last variable is the newest bound one."""

    def after(df: DataFrame, bound: list[str]) -> DataFrame:
        for f in p.filters:
            if bound[-1] not in f.vars or not set(f.vars) <= set(bound):
                continue
            if isinstance(f, Compare):
                right = F.col(f.right) if isinstance(f.right, str) else F.lit(f.right.value)
                left = F.col(f.left)
                df = df.where({"<": left < right, "<=": left <= right, ">": left > right, ">=": left >= right, "!=": left != right}[f.op])
            elif isinstance(f, Not):
                no = key_frame(f.atom, p.relations[f.atom.relation], list(f.vars), p.types)
                df = df.join(no.df, list(no.vars), "left_anti")
        return df

    return after


def settle(frames: list[KeyFrame], layouts: LayoutCatalog | None = None) -> list[KeyFrame]:
    """The frames written out and counted, atoms of one source once. layouts: keeps whole relations as sorted tables from query to query."""
    made: dict[tuple, tuple[DataFrame, int]] = {}
    out = []
    for f in frames:
        if f.rows is not None:
            out.append(f)
            continue
        if not f.source:
            df = cut(f.df, "frame")
            out.append(KeyFrame(f.name, f.vars, df, rows=df.count()))
            continue
        key = (f.source, tuple(sorted(f.columns)))
        if key not in made:
            named = f.df.select(*(F.col(v).alias(c) for c, v in sorted(zip(f.columns, f.vars, strict=True))))
            relation, conditions, *_ = f.source
            kept = layouts.build(relation, named, list(named.columns)) if layouts and not conditions else cut(named, "frame")
            made[key] = (kept, kept.count())
        kept, rows = made[key]
        out.append(KeyFrame(f.name, f.vars, kept.select(*(F.col(f"`{c}`").alias(v) for c, v in zip(f.columns, f.vars, strict=True))), f.source, f.columns, rows))
    return out


def planning_stats(frames: list[KeyFrame]) -> list[FrameStats]:
    """Estimates for the choice of order and engine, one small job a source."""
    known: dict[tuple, tuple[FrameStats, KeyFrame]] = {}
    out = []
    for i, f in enumerate(frames):
        key = (f.source, tuple(sorted(f.columns))) if f.source else (i,)
        if key not in known:
            known[key] = (frame_stats(f, exact=False), f)
        stats, of = known[key]
        if of is f:
            out.append(stats)
        else:
            at = {c: v for c, v in zip(of.columns, of.vars, strict=True)}
            out.append(FrameStats(stats.rows, {frozenset([v]): stats.distinct[frozenset([at[c]])] for c, v in zip(f.columns, f.vars, strict=True)}))
    return out


def heavy_values(frames: list[KeyFrame], shares: dict[str, int]) -> dict[str, list]:
    """Values that a cell cannot spread: of each variable with several shares those in more rows of an atom than its mean over the shares.
    There are fewer of them than shares for each atom, and one job with partial sums finds them."""
    tagged = None
    for f in frames:
        for v in f.vars:
            if shares.get(v, 1) > 1 and len(f.vars) > 1:
                one = f.df.groupBy(F.col(v).cast("long").alias("value")).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > max(1000, f.rows // shares[v])).select(F.lit(v).alias("var"), "value")
                tagged = one if tagged is None else tagged.unionByName(one)
    out: dict[str, list] = {}
    for r in tagged.distinct().collect() if tagged is not None else ():
        out.setdefault(r["var"], []).append(r["value"])
    return out


def split(frames: list[KeyFrame], var: str, heavy: DataFrame) -> tuple[list[KeyFrame], list[KeyFrame]]:
    """The frames without the heavy values of var, and those with them alone: disjoint, and together whole."""
    parts = []
    for how in ("left_anti", "left_semi"):
        parts.append([KeyFrame(f.name, f.vars, f.df.join(F.broadcast(heavy), var, how)) if var in f.vars else f for f in frames])
    return parts[0], parts[1]


def execute(p: Prepared, engine: str = "auto", order: list[str] | None = None, shares: dict[str, int] | None = None, driver: str = "per_prefix", cells: int = CELLS, keep: list | None = None, batch_rows: int = 1 << 16, measure: str | None = None, skew: str = "split", layouts: LayoutCatalog | None = None, costs: list | None = None, strategy: str = "exhaustive") -> DataFrame:
    """Distinct bindings of the head; measure="count": their number instead, as rows n to be summed.

    order: by default the one of least estimated cost. cells: how many at least; more are made if a cell would not fit a task. skew="split":
    values too frequent for a cell are found and joined apart by levels; "off" leaves them in.
    """
    if engine not in ENGINES:
        raise QueryError(f"no engine {engine!r}")
    spark, atoms = p.frames[0].df.sparkSession, [f.vars for f in p.frames]
    chosen = engine
    if engine == "auto" and len(atoms) > 1 and acyclic(atoms):
        chosen = "pairwise"
    frames = p.frames
    if chosen != "pairwise" and len(frames) > 1:
        frames = settle(frames, layouts)
    stats = planning_stats(frames) if len(frames) > 1 and chosen != "pairwise" and (order is None or engine == "auto") else None
    if order is None:
        order = choose_order(p.vars, atoms, stats, strategy) if stats and len(p.vars) > 2 else list(p.vars)
    frames = [f.of(order) for f in frames]
    atoms = [f.vars for f in frames]
    if chosen == "auto":
        chosen, found = choose_engine(atoms, [s.rows for s in stats], order, estimate_costs(order, atoms, stats), cells, layouts is not None) if stats else ("levels", None)
        shares = shares or found
    after = _filter(p)
    if chosen in ("levels", "hash"):
        about = {(i, v): s.distinct[frozenset([v])] for i, s in enumerate(stats or ()) for v in atoms[i]} if costs is None else None
        out = run_levels(spark, frames, order, chosen, driver, after, keep, costs, about)
    elif chosen == "pairwise":
        from .baselines import pairwise_frames

        out = pairwise_frames(frames, reduce=True).select(*order)
        for i in range(len(order)):
            out = after(out, order[: i + 1])
    else:
        frames = settle(frames)  # a query of one atom
        books = None
        if not whole_numbers(frames):
            frames, books = encode_frames(frames)
            frames = settle(frames)
        inside = "count" if measure == "count" and not p.filters else None
        if chosen == "cells":
            shares = shares or enough_cells(atoms, [f.rows for f in frames], order, cells)
            if shares is None:
                raise TooLarge("no grid of cells fits the tasks' memory; walk by levels")
            frequent = heavy_values(frames, shares) if skew == "split" and len(frames) > 1 else {}
            out = None
            while frequent:
                var, values = frequent.popitem()
                light, heavy = split(frames, var, spark.createDataFrame([(v,) for v in values], f"`{var}` long"))
                part = run_levels(spark, settle(heavy), [var, *(v for v in order if v != var)]).select(*(F.col(v).cast("long").alias(v) for v in order))
                part = part.agg(F.count(F.lit(1)).alias("n")) if inside else part
                out = part if out is None else out.unionByName(part)
                frames = settle(light)
            rest = run_cells(frames, order, shares, batch_rows, inside)
            out = rest if out is None else rest.unionByName(out)
        else:
            out = run_broadcast(spark, frames, order, batch_rows=batch_rows, measure=inside)
        if inside:
            return out
        out = decode(out, books) if books else out.select(*(F.col(v).cast(p.types.get(v, "long")).alias(v) for v in order))
        for i in range(len(order)):
            out = after(out, order[: i + 1])
    out = out.select(*p.head)
    return out.agg(F.count(F.lit(1)).alias("n")) if measure == "count" else out


def run(q: JoinQuery | str, relations: dict[str, DataFrame], engine: str = "levels", order: list[str] | None = None, **kw) -> DataFrame:
    """The answer of a rule over relations, distinct rows by construction. order: a permutation of the visible variables, by default
    that of the least estimated cost (strategy="appearance": as in the rule)."""
    return execute(prepare(q, relations, None), engine, order, **kw)


def run_split(q: JoinQuery | str, relations: dict[str, DataFrame], var: str, threshold: int, engine: str = "cells", **kw) -> DataFrame:
    """Skew split by hand: answers whose value of var is heavy (more than `threshold` rows in some atom) are found apart from the rest."""
    p = prepare(q, relations)
    heavy = None
    for f in p.frames:
        if var in f.vars:
            h = f.df.groupBy(var).count().where(F.col("count") > threshold).select(var)
            heavy = h if heavy is None else heavy.union(h)
    heavy = cut(heavy.distinct(), "heavy")
    light, rest = [], []
    for f in p.frames:
        light.append(KeyFrame(f.name, f.vars, f.df.join(heavy, var, "left_anti")) if var in f.vars else f)
        rest.append(KeyFrame(f.name, f.vars, f.df.join(heavy, var, "left_semi")) if var in f.vars else f)
    some = lambda frames, how: execute(Prepared(p.head, frames, p.filters, p.types, p.relations), how, **kw)
    return some(light, engine).unionByName(some(rest, "levels"))


def count(q: JoinQuery | str, relations: dict[str, DataFrame], order: list[str] | None = None, engine: str = "auto") -> DataFrame:
    """One row, n. Answers are not listed: where one atom alone gives the last variable its degrees are summed, else the last
    variable's values are counted where the walk finds them."""
    p = prepare(q, relations)
    atoms = [f.vars for f in p.frames]
    given = order or list(p.vars)
    last = level_plan(atoms, given)[-1]
    if not p.filters and len(last.participants) == 1 and len(given) > 1 and last.bound[0]:
        frames = settle(p.frames)
        rest = [KeyFrame(f.name, tuple(v for v in f.vars if v != last.var), f.df.select(*(v for v in f.vars if v != last.var)).distinct()) for f in frames if set(f.vars) != {last.var}]
        prefix = execute(Prepared(tuple(given[:-1]), rest, [], p.types, p.relations), "auto", given[:-1])
        deg = Projections(frames).degrees(last.participants[0], last.bound[0], last.var, "deg")
        return prefix.join(deg, [*last.bound[0]]).agg(F.coalesce(F.sum("deg"), F.lit(0)).cast("long").alias("n"))
    return execute(p, engine, order, measure="count").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def exists(q: JoinQuery | str, relations: dict[str, DataFrame], **kw) -> bool:
    return bool(run(q, relations, **kw).limit(1).count())


def first(q: JoinQuery | str, relations: dict[str, DataFrame], n: int, **kw) -> DataFrame:
    """n answers, whichever come first."""
    return run(q, relations, **kw).limit(n)


class Answer:
    """An answer as a trie over its variables: prefixes of a depth, and the children of a prefix."""

    def __init__(self, df: DataFrame):
        self.df = df

    def prefix(self, depth: int) -> DataFrame:
        return self.df.select(*self.df.columns[:depth]).distinct()

    def children(self, values: tuple) -> DataFrame:
        df = self.df
        for c, v in zip(df.columns, values, strict=False):
            df = df.where(F.col(c) == F.lit(v))
        return df.select(self.df.columns[len(values)]).distinct()


def attach(answer: DataFrame, rel: DataFrame, on: dict[str, str], cols: list[str]) -> DataFrame:
    """Payload columns of a relation joined to answers last, on its keys: on = {variable: column}."""
    right = rel.select(*(F.col(c).alias(f"_{v}") for v, c in on.items()), *cols)
    cond = None
    for v in on:
        c = answer[v] == right[f"_{v}"]
        cond = c if cond is None else cond & c
    return answer.join(right, cond).drop(*(f"_{v}" for v in on))


def explain(q: JoinQuery | str, relations: dict[str, DataFrame], order: list[str] | None = None) -> str:
    """Order, levels, sizes, bound, estimated costs, engine and shares as text."""
    p = prepare(q, relations)
    stats = planning_stats(p.frames)
    sizes, atoms = [s.rows for s in stats], [f.vars for f in p.frames]
    order = order or choose_order(p.vars, atoms, stats)
    costs = estimate_costs(order, atoms, stats)
    engine, shares = choose_engine(atoms, sizes, order, costs, CELLS)
    bound, weights = cover_bound(p.edges, sizes)
    lines = [f"order: {', '.join(order)}", f"bound: {bound:.2f} (weights {', '.join(map(str, weights))})", f"engine: {engine}, shares {shares}"]
    for level, c in zip(level_plan(atoms, order), costs, strict=True):
        who = ", ".join(f"{p.frames[i].name}[{','.join(b) or '-'}]" for i, b in zip(level.participants, level.bound, strict=True))
        lines.append(f"level {level.var}: {who}; estimated cost {c:.0f}")
    return "\n".join(lines)


__all__ = ["Answer", "Const", "attach", "count", "execute", "exists", "explain", "first", "prepare", "run", "run_split"]
