"""Cost measures: level costs, prefix sizes, moves, and the certificate that relates them to the bound."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel.cursor import OpCounter
from ..kernel.hashwalk import hash_walk
from ..kernel.walk import count_moves
from ..plans.bounds import cover_bound
from ..plans.levels import level_plan
from ..plans.rewrite import KeyFrame
from .broadcast_engine import TooLarge
from .engine import Prepared, settle
from .level_engine import run_levels

#: Rows that a scalar walk may bring to the driver: it counts moves, it is no engine.
LOCAL_ROWS = 2_000_000


def level_costs(p: Prepared, order: list[str], engine: str = "levels") -> list[tuple[str, int, int]]:
    """(variable, level cost, prefixes found) of each level: the cost is the sum of the smallest slice over the prefixes before. It is
    summed from the degrees that the walk itself writes."""
    frames, keep, costs = [f.of(order) for f in settle(p.frames)], [], []
    run_levels(p.frames[0].df.sparkSession, frames, order, engine, keep=keep, costs=costs)
    return [(v, int(c), prefix.count()) for v, c, prefix in zip(order, costs, keep, strict=True)]


def costs_frame(p: Prepared, order: list[str]) -> DataFrame:
    rows = [(i, v, c, n) for i, (v, c, n) in enumerate(level_costs(p, order))]
    return p.frames[0].df.sparkSession.createDataFrame(rows, "level int, var string, c long, n_rows long")


def all_order_costs(p: Prepared) -> DataFrame:
    """The sum of level costs in every order."""
    p = Prepared(p.head, settle(p.frames), p.filters, p.types, p.relations)
    rows = [(",".join(o), sum(c for _, c, _ in level_costs(p, list(o)))) for o in permutations(p.vars)]
    return p.frames[0].df.sparkSession.createDataFrame(rows, "variable_order string, total long")


def local_atoms(p: Prepared, order: list[str]) -> list[tuple[list[int], list[tuple]]]:
    """Atoms as Python rows for the scalar kernels, which run on the driver and are for LOCAL_ROWS rows at most."""
    frames = settle(p.frames)
    if sum(f.rows for f in frames) > LOCAL_ROWS:
        raise TooLarge(f"{sum(f.rows for f in frames)} rows for a scalar walk on the driver; {LOCAL_ROWS} are allowed")
    out = []
    for f in frames:
        vs = [v for v in order if v in f.vars]
        out.append(([order.index(v) for v in vs], [tuple(r) for r in f.df.select(*vs).collect()]))
    return out


def ops_frame(p: Prepared, order: list[str]) -> DataFrame:
    """Moves of the scalar walk by kind and level, and probes of the hash walk."""
    atoms = local_atoms(p, order)
    _, ops = count_moves(atoms, len(order))
    hashed = OpCounter()
    for _ in hash_walk(atoms, len(order), hashed):
        pass
    rows = sorted((k, level, n) for (k, level), n in [*ops.by.items(), *hashed.by.items()])
    return p.frames[0].df.sparkSession.createDataFrame(rows, "kind string, level int, n long")


def compare_density(p: Prepared, order: list[str]) -> tuple[int, int]:
    """(skips and steps of the sorted walk, probes of the hash walk)."""
    rows = ops_frame(p, order).collect()
    return sum(r["n"] for r in rows if r["kind"] in ("step", "skip")), sum(r["n"] for r in rows if r["kind"] == "probe")


def certify(p: Prepared, order: list[str], moves: bool = False) -> dict:
    """Level costs, prefix sizes and the bound, and whether prefixes <= costs <= bound holds; with the moves of the scalar walk if asked."""
    if p.filters:
        raise ValueError("the bound is for full conjunctive queries")
    sizes = [f.df.count() for f in p.frames]
    bound, weights = cover_bound(p.edges, sizes)
    levels = level_costs(p, order)
    out = {"sizes": sizes, "bound": bound, "weights": weights, "levels": levels, "ok": all(n <= c <= bound * (1 + 1e-9) for _, c, n in levels)}
    if moves:
        _, ops = count_moves(local_atoms(p, order), len(order))
        most = max(len(x.participants) for x in level_plan([f.vars for f in p.frames], order))
        nodes = 1 + sum(n for _, _, n in levels[:-1])
        out |= {"linear": ops.total("step", "skip"), "vertical": ops.total("open", "up")}
        out["ok"] = out["ok"] and out["linear"] <= most * (sum(c for _, c, _ in levels) + nodes) and ops.total("open") <= len(p.frames) * nodes
    return out


def diff(a: DataFrame, b: DataFrame) -> tuple[int, int]:
    """Rows of a missing in b, and the other way round."""
    return a.exceptAll(b).count(), b.exceptAll(a).count()


def frames_of(**rows: DataFrame) -> list[KeyFrame]:
    return [KeyFrame(n, tuple(df.columns), df) for n, df in rows.items()]
