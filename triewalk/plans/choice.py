"""Engine and shares by arithmetic over sizes."""

from __future__ import annotations

import math

#: Bytes of a key column's value in flight, and what one cell may hold in a task.
VALUE_BYTES, CELL_BYTES = 16, 256 << 20
BROADCAST_ROWS = 2_000_000
MOST_CELLS = 1 << 16


def _steps(left: int) -> list[int]:
    out, p = [], 1
    while p <= left:
        out.append(p)
        p += 1 if p < 8 else p // 4
    return out


def best_shares(atoms: list[tuple[str, ...]], sizes: list[int], order: list[str], cells: int) -> dict[str, int]:
    """Whole shares with a product of at most `cells` that give the least load of a cell, and of those the least traffic."""
    best, found = None, dict.fromkeys(order, 1)

    def go(i: int, left: int, shares: dict[str, int]) -> None:
        nonlocal best, found
        if i == len(order):
            load = sum(n / math.prod(shares[v] for v in vs) for vs, n in zip(atoms, sizes, strict=True))
            score = (load, traffic(atoms, sizes, shares))
            if best is None or score < best:
                best, found = score, dict(shares)
            return
        for p in _steps(left):
            go(i + 1, left // p, shares | {order[i]: p})

    go(0, cells, {})
    return found


def traffic(atoms: list[tuple[str, ...]], sizes: list[int], shares: dict[str, int]) -> float:
    """Rows that the grid shuffle sends: each row to every cell along the variables that its atom lacks."""
    cells = math.prod(shares.values())
    return sum(n * cells / math.prod(shares[v] for v in vs) for vs, n in zip(atoms, sizes, strict=True))


def cell_load(atoms: list[tuple[str, ...]], sizes: list[int], shares: dict[str, int]) -> float:
    """Bytes of one cell, if keys spread evenly."""
    return sum(n * len(vs) * VALUE_BYTES / math.prod(shares[v] for v in vs) for vs, n in zip(atoms, sizes, strict=True))


def enough_cells(atoms: list[tuple[str, ...]], sizes: list[int], order: list[str], least: int) -> dict[str, int] | None:
    """Shares of the least number of cells, doubled from `least`, whose load fits a task; None if MOST_CELLS are not enough."""
    cells = least
    while cells <= MOST_CELLS:
        shares = best_shares(atoms, sizes, order, cells)
        if cell_load(atoms, sizes, shares) <= CELL_BYTES:
            return shares
        cells *= 4
    return None


def acyclic(atoms: list[tuple[str, ...]]) -> bool:
    """Whether ears can be taken off until nothing is left."""
    edges = [set(a) for a in atoms]
    while True:
        before = [set(e) for e in edges]
        for e in edges:
            e -= {v for v in e if sum(v in f for f in edges) == 1}
        edges = [e for i, e in enumerate(edges) if e and not any((e < f) or (e == f and j < i) for j, f in enumerate(edges) if j != i)]
        if not edges:
            return True
        if edges == before:
            return False


def choose_engine(atoms: list[tuple[str, ...]], sizes: list[int], order: list[str], costs: list[float], cells: int, sorted_already: bool = False) -> tuple[str, dict[str, int]]:
    """(engine, shares): binary joins for acyclic queries, broadcast when all atoms but the largest are small, else the cheaper of cells
    and a walk by levels, sorted or hashed by density."""
    if len(atoms) > 1 and acyclic(atoms):
        return "pairwise", dict.fromkeys(order, 1)
    shares = enough_cells(atoms, sizes, order, cells)
    if sum(sizes) - max(sizes) <= BROADCAST_ROWS:
        return "broadcast", shares or dict.fromkeys(order, 1)
    by_levels = sum(c * (1 + sum(v in vs for vs in atoms)) for c, v in zip(costs, order, strict=True)) + 2 * sum(sizes)
    if shares and traffic(atoms, sizes, shares) < by_levels:
        return "cells", shares
    return density_choice(max(sizes), min(sizes), sorted_already), shares or dict.fromkeys(order, 1)


def density_choice(nmax: int, nmin: int, sorted_already: bool) -> str:
    """Sorted or hashed for a level: a sorted layout at hand or near-equal densities favour order; a one-off sparse probe favours hashing."""
    return "levels" if sorted_already or nmax <= 4 * max(1, nmin) else "hash"
