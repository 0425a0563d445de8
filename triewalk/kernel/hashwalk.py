"""The walk over nested hash tables: the smallest table of a level is scanned, the others are probed."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from .cursor import OpCounter


def hash_trie(rows: Iterable[tuple]) -> dict:
    """A table from each first value to the table of the rest; the last column's values lead to nothing."""
    root: dict = {}
    for row in rows:
        node = root
        for v in row:
            node = node.setdefault(v, {})
    return root


def hash_meet(tables: list[dict], ops: OpCounter, level: int = 0) -> Iterator:
    """Keys of all tables: those of the smallest that every other one has; each look-up is a probe."""
    small, *rest = sorted(tables, key=len)
    for v in small:
        ok = True
        for t in rest:
            ops.note("probe", level)
            if v not in t:
                ok = False
                break
        if ok:
            yield v


def hash_walk(atoms: list[tuple[list[int], Iterable[tuple]]], k: int, ops: OpCounter) -> Iterator[tuple]:
    """Bindings of all variables, in no order. atoms: (positions of its variables in the order, rows)."""
    levels = [[i for i, (at, _) in enumerate(atoms) if v in at] for v in range(k)]

    def below(depth: int, bound: tuple, nodes: list[dict]) -> Iterator[tuple]:
        parts = levels[depth]
        for v in hash_meet([nodes[i] for i in parts], ops, depth):
            if depth + 1 == k:
                yield (*bound, v)
            else:
                yield from below(depth + 1, (*bound, v), [n[v] if i in parts else n for i, n in enumerate(nodes)])

    yield from below(0, (), [hash_trie(rows) for _, rows in atoms])
