from fractions import Fraction

import pytest

from triewalk.plans import bounds
from triewalk.plans.choice import acyclic, best_shares, choose_engine, traffic
from triewalk.plans.ir import ArityMismatch, Atom, Compare, Const, Exists, ForAll, JoinQuery, Not, Or, QueryError, UnknownRelation, UnorderedType, UnsafeVariable, UnsupportedFormula, analyze
from triewalk.plans.levels import level_plan
from triewalk.plans.order import choose_order
from triewalk.plans.parse import rule
from triewalk.plans.rewrite import alias_self_joins, align_columns, lift_constants, split_repeats
from triewalk.plans.stats import FrameStats

TRI = [("a", "b"), ("b", "c"), ("a", "c")]
EDGES = [frozenset(x) for x in TRI]


def test_parse():
    q = rule("Q(a,b) :- R(a,b), not S(b), a < b, (V(a) ; W(a)), X(a, 2, 'p').")
    assert q.head == ("a", "b")
    assert q.body[1:3] == (Not(Atom("S", ("b",))), Compare("<", "a", "b"))
    assert isinstance(q.body[3], Or) and q.body[4] == Atom("X", ("a", Const(2), Const("p")))
    for bad in ("Q(a)", "Q(1) :- R(a)", "Q(a) :- R(a", "Q(a) :- R(a) R(b)"):
        with pytest.raises(QueryError):
            rule(bad)


def test_rewrites():
    q, equal = split_repeats(rule("Q(x) :- R(x,x)"))
    assert q.body[0].terms == ("x", "x__0") and equal == [("x", "x__0")]
    q, values = lift_constants(rule("Q(x) :- A(x,2)"))
    assert q.body[0].terms == ("x", "const__0") and values == {"const__0": 2}
    q, names = alias_self_joins(rule("Q(x,y,z) :- E(x,y), E(y,z)"))
    assert [a.relation for a in q.atoms] == ["E", "E__2"] and names["E__2"] == "E"
    assert align_columns(Atom("U", ("c", "a")), ["a", "b", "c"]) == (1, 0)


def test_levels():
    plan = level_plan(TRI, ["a", "b", "c"])
    assert [x.participants for x in plan] == [(0, 2), (0, 1), (1, 2)]
    assert plan[2].bound == (("b",), ("a",))


def test_bounds():
    assert bounds.cover_bound(EDGES, [100] * 3) == (pytest.approx(1000), [Fraction(1, 2)] * 3)
    assert bounds.cover_bound(EDGES, [1444, 10, 150])[0] == pytest.approx(1471.7337, abs=1e-3)
    assert bounds.cover_bound(EDGES, [1, 5, 0])[0] == 0
    n = 256
    small = {frozenset("a"): 8, frozenset("b"): 32, frozenset("c"): 1}
    assert bounds.projection_bound(EDGES, [n, n, n], small) == pytest.approx(n)
    assert bounds.meet_cost([4, 16]) == 12 and bounds.meet_cost([0, 3]) == 0
    assert bounds.growth_exponent([(4, 8), (16, 64), (64, 512)]) == pytest.approx(1.5)
    assert bounds.predicted_cost([1, 2], 8) == 9 and bounds.pairs_bound_formula(10, 3) == 300


def test_orders_and_choice():
    stats = [FrameStats(48518, {frozenset("a"): 1500, frozenset("b"): 100}), FrameStats(100, {frozenset("b"): 100, frozenset("c"): 25}), FrameStats(1500, {frozenset("a"): 1500, frozenset("c"): 25})]
    order = choose_order(("a", "b", "c"), TRI, stats)
    assert set(order[:2]) == {"b", "c"}
    assert sorted(choose_order(("a", "b", "c"), TRI, stats, "greedy")) == ["a", "b", "c"]
    assert choose_order(("a", "b", "c"), TRI, None, "given", ["c", "a", "b"]) == ["c", "a", "b"]
    with pytest.raises(ValueError):
        choose_order(("a",), TRI, None, "given", ["z"])
    assert best_shares(TRI, [1000, 1000, 1000], ["a", "b", "c"], 8) == {"a": 2, "b": 2, "c": 2}
    assert traffic(TRI, [10, 10, 10], {"a": 2, "b": 2, "c": 2}) == 60
    assert acyclic([("a", "b"), ("b", "c")]) and not acyclic(TRI)
    assert choose_engine([("a", "b"), ("b", "c")], [5, 5], ["a", "b", "c"], [1, 1, 1], 8)[0] == "pairwise"
    assert choose_engine(TRI, [10**9, 10, 10], ["a", "b", "c"], [1, 1, 1], 8)[0] == "broadcast"
    assert choose_engine(TRI, [10**12] * 3, ["a", "b", "c"], [1e12] * 3, 8)[0] == "levels"


def test_analysis(spark):
    rels = {"R": spark.range(1).selectExpr("id as a", "id as b"), "M": spark.sql("select map(1, 2) as m"), "S": spark.range(1)}
    for q, error in (
        ("Q(a) :- X(a)", UnknownRelation),
        ("Q(a) :- R(a)", ArityMismatch),
        ("Q(a) :- M(a)", UnorderedType),
        ("Q(z) :- R(a,b)", UnsafeVariable),
        ("Q(a) :- R(a,b), not S(z)", UnsafeVariable),
        ("Q(a) :- R(a,b), (S(a) ; S(b))", UnsafeVariable),
        ("Q(a) :- R(a,'x')", QueryError),
    ):
        with pytest.raises(error):
            analyze(rule(q), rels)
    with pytest.raises(UnsupportedFormula):
        analyze(JoinQuery.of("a", Atom("R", ("a", "b")), ForAll(("b",), Atom("S", ("b",)))), rels)
    with pytest.raises(UnsupportedFormula):
        analyze(JoinQuery.of("a", Atom("R", ("a", "b")), Not(Exists(("c",), Atom("R", ("a", "c"))))), rels)
