"""Rule text to queries: Q(a,b,c) :- R(a,b), S(b,c), T(a,c), not U(c), a < b, (V(a) ; W(a))."""

from __future__ import annotations

import re

from .ir import And, Atom, Compare, Const, JoinQuery, Not, Or, QueryError

_TOKEN = re.compile(r"\s*(:-|<=|>=|!=|[<>(),;.]|not\b|-?\d+\.\d+|-?\d+|'[^']*'|[A-Za-z_]\w*)")


def _tokens(text: str) -> list[str]:
    out, at = [], 0
    while at < len(text.rstrip()):
        m = _TOKEN.match(text, at)
        if not m:
            raise QueryError(f"cannot read {text[at:at + 20]!r}")
        out.append(m[1])
        at = m.end()
    return out


class _Reader:
    def __init__(self, tokens: list[str]):
        self.tokens, self.at = tokens, 0

    def peek(self, ahead: int = 0) -> str:
        return self.tokens[self.at + ahead] if self.at + ahead < len(self.tokens) else ""

    def take(self, want: str = "") -> str:
        t = self.peek()
        if not t or want and t != want:
            raise QueryError(f"expected {want or 'more'}, found {t or 'the end'}")
        self.at += 1
        return t

    def term(self):
        t = self.take()
        if t[0] == "'":
            return Const(t[1:-1])
        if re.fullmatch(r"-?\d+", t):
            return Const(int(t))
        if re.fullmatch(r"-?\d+\.\d+", t):
            return Const(float(t))
        return t

    def atom(self) -> Atom:
        name = self.take()
        self.take("(")
        terms = [self.term()]
        while self.peek() == ",":
            self.take()
            terms.append(self.term())
        self.take(")")
        return Atom(name, tuple(terms))

    def part(self):
        if self.peek() == "not":
            self.take()
            return Not(self.atom())
        if self.peek() == "(":
            self.take()
            arms = [self.conjunction()]
            while self.peek() == ";":
                self.take()
                arms.append(self.conjunction())
            self.take(")")
            return Or(tuple(arms)) if len(arms) > 1 else arms[0]
        if self.peek(1) in ("<", "<=", ">", ">=", "!="):
            left = self.take()
            op = self.take()
            return Compare(op, left, self.term())
        return self.atom()

    def conjunction(self):
        parts = [self.part()]
        while self.peek() == ",":
            self.take()
            parts.append(self.part())
        return parts[0] if len(parts) == 1 else And(tuple(parts))


def rule(text: str) -> JoinQuery:
    """The query of a rule; variables of the body that the head lacks are projected out."""
    r = _Reader(_tokens(text))
    head = r.atom()
    r.take(":-")
    body = r.conjunction()
    if r.peek() == ".":
        r.take()
    if r.peek():
        raise QueryError(f"left over: {r.peek()}")
    if any(not isinstance(t, str) for t in head.terms):
        raise QueryError("the head takes variables only")
    return JoinQuery(head.terms, body.parts if isinstance(body, And) else (body,))
