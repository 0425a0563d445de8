"""Variable orders. Any permutation gives the answer and the bound; estimates only choose among them."""

from __future__ import annotations

from itertools import permutations

from .stats import FrameStats


def estimate_costs(order: list[str], atoms: list[tuple[str, ...]], stats: list[FrameStats]) -> list[float]:
    """Estimated level costs: prefixes times the smallest mean slice, with independence between atoms."""
    prefixes, out = 1.0, []
    for i, v in enumerate(order):
        slices, domain = [], []
        for vs, s in zip(atoms, stats, strict=True):
            if v not in vs:
                continue
            bound = [x for x in order[:i] if x in vs]
            below = s.rows
            for x in vs:
                if x != v and x not in bound:
                    below = max(1, below / max(1, s.rows / max(1, _upto(s, [*bound, v]))))
            known = max(1, _upto(s, bound)) if bound else 1
            slices.append(max(1e-9, _upto(s, [*bound, v]) / known))
            domain.append(max(1, s.distinct[frozenset([v])]))
        least = min(slices)
        out.append(prefixes * least)
        keep = 1.0
        for x in slices:
            keep *= min(1.0, x / max(domain))
        prefixes = max(1.0, prefixes * max(domain) * keep)
    return out


def _upto(s: FrameStats, vs: list[str]) -> float:
    """Distinct values of a set of columns, no more than rows and the product of the single counts."""
    n = 1.0
    for v in vs:
        n *= max(1, s.distinct[frozenset([v])])
    return min(float(s.rows), n)


def choose_order(vars_: tuple[str, ...], atoms: list[tuple[str, ...]], stats: list[FrameStats] | None, strategy: str = "exhaustive", given: list[str] | None = None) -> list[str]:
    """given: as told; appearance: as in the query; exhaustive (up to 7 variables) and greedy: least estimated sum of level costs."""
    if strategy == "given" or given:
        if sorted(given or []) != sorted(vars_):
            raise ValueError(f"an order must be a permutation of {vars_}")
        return list(given)
    if strategy == "appearance" or not stats:
        return list(vars_)
    if strategy == "exhaustive" and len(vars_) <= 7:
        return list(min(permutations(vars_), key=lambda o: sum(estimate_costs(list(o), atoms, stats))))
    order: list[str] = []
    while len(order) < len(vars_):
        rest = [v for v in vars_ if v not in order]
        near = [v for v in rest if any(v in vs and set(order) & set(vs) for vs in atoms)] or rest
        order.append(min(near, key=lambda v: sum(estimate_costs([*order, v], atoms, stats))))
    return order
