"""The four rewrites to the restricted form: no repeated variable in an atom, arguments in the variable order, one symbol an
atom, no constants; and lowering of atoms to frames of distinct, non-null keys."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ir import Atom, Const, JoinQuery, common_type, tidy


@dataclass
class KeyFrame:
    """An atom made ready: vars in the variable order and a frame with a column of that name each, distinct and without nulls.

    source: what the frame is made of but for the names of its columns, if that is known, and the relation's column of each variable; two
    atoms of one source are one table under two names. rows: how many, once they are written out.
    """

    name: str
    vars: tuple[str, ...]
    df: DataFrame
    source: tuple | None = None
    columns: tuple[str, ...] = ()
    rows: int | None = None

    def of(self, order: list[str]) -> KeyFrame:
        """The frame with its columns in another order of variables."""
        vs = tuple(v for v in order if v in self.vars)
        return KeyFrame(self.name, vs, self.df.select(*vs), self.source, tuple(self.columns[self.vars.index(v)] for v in vs) if self.columns else (), self.rows)


def split_repeats(q: JoinQuery) -> tuple[JoinQuery, list[tuple[str, str]]]:
    """Fresh variables for repeats in an atom, and the pairs that must be equal."""
    fresh, equal, body = count(), [], []
    for p in q.body:
        if isinstance(p, Atom):
            seen, terms = set(), []
            for t in p.terms:
                if isinstance(t, str) and t in seen:
                    new = f"{t}__{next(fresh)}"
                    equal.append((t, new))
                    t = new
                if isinstance(t, str):
                    seen.add(t)
                terms.append(t)
            p = Atom(p.relation, tuple(terms))
        body.append(p)
    return q.with_body(body), equal


def lift_constants(q: JoinQuery) -> tuple[JoinQuery, dict[str, object]]:
    """Fresh variables for constants, and the value of each."""
    fresh, values, body = count(), {}, []
    for p in q.body:
        if isinstance(p, Atom):
            terms = []
            for t in p.terms:
                if isinstance(t, Const):
                    name = f"const__{next(fresh)}"
                    values[name] = t.value
                    t = name
                terms.append(t)
            p = Atom(p.relation, tuple(terms))
        body.append(p)
    return q.with_body(body), values


def alias_self_joins(q: JoinQuery) -> tuple[JoinQuery, dict[str, str]]:
    """A name of its own for each atom, and which relation each copy stands for."""
    seen: dict[str, int] = {}
    names, body = {}, []
    for p in q.body:
        if isinstance(p, Atom):
            n = seen[p.relation] = seen.get(p.relation, 0) + 1
            name = p.relation if n == 1 else f"{p.relation}__{n}"
            names[name] = p.relation
            p = Atom(name, p.terms)
        body.append(p)
    return q.with_body(body), names


def align_columns(atom: Atom, order: list[str]) -> tuple[int, ...]:
    """Which column of the atom stands at each place once its arguments follow the order (atoms of distinct variables)."""
    return tuple(sorted(range(len(atom.terms)), key=lambda i: order.index(atom.terms[i])))


def key_frame(atom: Atom, df: DataFrame, order: list[str], types: dict, name: str | None = None, unique: bool = False) -> KeyFrame:
    """The atom as a frame: constants and repeated variables become filters on the scan, columns follow the order.

    unique: the relation is known to hold no repeated rows, so no shuffle is spent on removing them.
    """
    columns, made_of = df.columns, df.semanticHash()
    first: dict[str, str] = {}
    conditions = []
    for c, t in zip(columns, atom.terms, strict=True):
        col = F.col(f"`{c}`")
        if isinstance(t, Const):
            df = df.where(col == F.lit(t.value))
            conditions.append((c, "is", repr(t.value)))
        elif t in first:
            df = df.where(col == F.col(f"`{first[t]}`"))
            conditions.append((c, "same", first[t]))
        else:
            first[t] = c
    vars_ = tuple(v for v in order if v in first)
    kinds = tuple(sorted((first[v], str(types[v])) for v in vars_))
    out = df.select(*(tidy(F.col(f"`{first[v]}`").cast(types[v]), types[v]).alias(v) for v in vars_)).dropna()
    whole = unique and len(vars_) == len(columns)
    return KeyFrame(name or atom.relation, vars_, out if whole else out.distinct(), (atom.relation, tuple(conditions), kinds, made_of), tuple(first[v] for v in vars_))


def variable_types(q: JoinQuery, relations: dict[str, DataFrame]) -> dict:
    kinds: dict[str, list] = {}

    def visit(p) -> None:
        for x in getattr(p, "parts", ()) or ([p.body] if hasattr(p, "body") else []) or ([p.atom] if hasattr(p, "atom") else []):
            visit(x)
        if isinstance(p, Atom):
            for f, t in zip(relations[p.relation].schema.fields, p.terms, strict=True):
                if isinstance(t, str):
                    kinds.setdefault(t, []).append(f.dataType)

    for p in q.body:
        visit(p)
    return {v: common_type(ts) for v, ts in kinds.items()}
