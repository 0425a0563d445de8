"""Which atoms take part in each variable's meet, and which of their columns are bound by then."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Level:
    var: str
    participants: tuple[int, ...]
    bound: tuple[tuple[str, ...], ...]  # of each participant, its variables before this one


def level_plan(atoms: list[tuple[str, ...]], order: list[str]) -> list[Level]:
    """atoms: the variables of each atom."""
    out = []
    for i, v in enumerate(order):
        parts = tuple(k for k, vs in enumerate(atoms) if v in vs)
        out.append(Level(v, parts, tuple(tuple(x for x in order[:i] if x in atoms[k]) for k in parts)))
    return out
