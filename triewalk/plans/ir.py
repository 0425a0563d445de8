"""Queries: atoms over named relations, comparisons, complements, alternatives and hidden variables; and their analysis."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class QueryError(ValueError):
    """A query that cannot be run."""


class UnknownRelation(QueryError): ...


class ArityMismatch(QueryError): ...


class UnorderedType(QueryError): ...


class UnsafeVariable(QueryError): ...


class UnsupportedFormula(QueryError): ...


@dataclass(frozen=True)
class Const:
    value: object


@dataclass(frozen=True)
class Atom:
    """A relation with a variable name or a constant at each place."""

    relation: str
    terms: tuple

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t for t in self.terms if isinstance(t, str)))


@dataclass(frozen=True)
class Not:
    """A complement: no row of the relation has the values bound elsewhere."""

    atom: Atom

    @property
    def vars(self) -> tuple[str, ...]:
        return self.atom.vars


@dataclass(frozen=True)
class Compare:
    op: str
    left: str
    right: object  # a variable's name or a Const

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(x for x in (self.left, self.right) if isinstance(x, str))


@dataclass(frozen=True)
class And:
    parts: tuple

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for p in self.parts for v in p.vars))


@dataclass(frozen=True)
class Or:
    """Alternatives over the same variables."""

    parts: tuple

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for p in self.parts for v in p.vars))


@dataclass(frozen=True)
class Exists:
    hidden: tuple[str, ...]
    body: object

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(v for v in self.body.vars if v not in self.hidden)


@dataclass(frozen=True)
class ForAll:
    hidden: tuple[str, ...]
    body: object

    @property
    def vars(self) -> tuple[str, ...]:
        return self.body.vars


@dataclass(frozen=True)
class JoinQuery:
    """head: visible variables in order; body: conjunction; hidden variables of the body are projected out."""

    head: tuple[str, ...]
    body: tuple = field(default=())

    @classmethod
    def of(cls, head: str, *body) -> JoinQuery:
        return cls(tuple(head.split()), tuple(body))

    @property
    def atoms(self) -> tuple[Atom, ...]:
        return tuple(p for p in self.body if isinstance(p, Atom))

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys([*self.head, *(v for p in self.body for v in p.vars)]))

    @property
    def full(self) -> bool:
        """Whether it is a full conjunction of atoms, for which the bounds hold."""
        return all(isinstance(p, Atom) for p in self.body) and set(self.head) == set(self.vars)

    def with_body(self, body) -> JoinQuery:
        return replace(self, body=tuple(body))


_UNORDERED = (T.MapType, T.CalendarIntervalType)


def _check(part, relations: dict[str, DataFrame], negated: bool) -> None:
    if isinstance(part, ForAll):
        raise UnsupportedFormula("universal quantifiers are outside the language")
    if isinstance(part, Exists):
        if negated:
            raise UnsupportedFormula("a complement may not hide variables")
        return _check(part.body, relations, negated)
    if isinstance(part, And | Or):
        for p in part.parts:
            _check(p, relations, negated)
        if isinstance(part, Or) and len({frozenset(p.vars) for p in part.parts}) > 1:
            raise UnsafeVariable("the alternatives of a union must bind the same variables")
        return None
    if isinstance(part, Not):
        if not isinstance(part.atom, Atom):
            raise UnsupportedFormula("only an atom may be complemented")
        return _check(part.atom, relations, True)
    if isinstance(part, Compare):
        return None
    if part.relation not in relations:
        raise UnknownRelation(part.relation)
    fields = relations[part.relation].schema.fields
    if len(fields) != len(part.terms):
        raise ArityMismatch(f"{part.relation} has {len(fields)} columns, the atom {len(part.terms)}")
    for f, t in zip(fields, part.terms, strict=True):
        if isinstance(f.dataType, _UNORDERED) or type(f.dataType).__name__ == "VariantType":
            raise UnorderedType(f"{part.relation}.{f.name} is of type {f.dataType.simpleString()}, which has no order")
        if isinstance(t, Const) and isinstance(t.value, str) != isinstance(f.dataType, T.StringType):
            raise QueryError(f"the constant {t.value!r} does not fit {part.relation}.{f.name}")
    return None


def analyze(q: JoinQuery, relations: dict[str, DataFrame]) -> JoinQuery:
    """Checks names, arities, types and that every variable is bound by a positive part; returns q."""
    for p in q.body:
        _check(p, relations, False)
    bound = {v for p in q.body if isinstance(p, Atom | And | Or | Exists) for v in p.vars}
    loose = [v for p in q.body if isinstance(p, Not | Compare) for v in p.vars if v not in bound]
    if loose or any(v not in bound for v in q.head):
        raise UnsafeVariable(f"not bound by a positive part: {loose or [v for v in q.head if v not in bound]}")
    return q


def common_type(types: list[T.DataType]) -> T.DataType:
    """The type of a variable: the widest of its columns."""
    kinds = {t.simpleString() for t in types}
    if len(kinds) == 1:
        return types[0]
    whole = ("tinyint", "smallint", "int", "bigint")
    if kinds <= set(whole):
        return T.LongType()
    if kinds <= {*whole, "float", "double"}:
        return T.DoubleType()
    raise QueryError(f"columns of one variable have types {sorted(kinds)}")


def tidy(column, kind: T.DataType):
    """Floats: -0.0 counts as 0.0 (NaN is one value in Spark already)."""
    return F.when(column == 0, F.lit(0.0).cast(kind)).otherwise(column) if isinstance(kind, T.FloatType | T.DoubleType) else column
