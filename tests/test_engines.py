"""Engines agree with each other, with brute force and with the golden sizes."""

import random
import re
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from triewalk import workloads as W
from triewalk.operators import baselines, costs, families, layout, level_engine, renumber, skip_meet
from triewalk.operators.broadcast_engine import TooLarge, run_broadcast
from triewalk.operators.cell_engine import assign, pack, run_cells, unpack
from triewalk.operators.domain import encode_domain
from triewalk.operators.engine import Answer, attach, count, execute, exists, explain, first, heavy_values, prepare, run, run_split, settle
from triewalk.plans import choice
from triewalk.plans.ir import Atom, JoinQuery
from triewalk.sources.synthetic import density_instance, grid, projection_instance
from triewalk.sources.tables import load, relation

from .conftest import SMALL

TRI = W.TRIANGLE


def pairs(spark, rows, names="x y"):
    a, b = names.split()
    return spark.createDataFrame(rows, f"{a} long, {b} long")


def got(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("engine", ["levels", "hash", "cells", "broadcast", "pairwise", "auto"])
def test_engines_on_random_edges(spark, engine):
    rng = random.Random(7)
    rows = [(rng.randint(0, 12), rng.randint(0, 12)) for _ in range(70)] + [(0, 1)] * 3 + [(None, 1), (1, None)]
    edges = {(a, b) for a, b in rows if a is not None and b is not None}
    want = sorted((a, b, c) for a, b in edges for x, c in edges if x == b and (a, c) in edges)
    assert got(run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": pairs(spark, rows)}, engine)) == want


def test_all_orders_drivers_and_brute(spark):
    rng = random.Random(1)
    make = lambda: pairs(spark, [(rng.randint(0, 6), rng.randint(0, 6)) for _ in range(18)])
    rels = {"R": make(), "S": make(), "T": make()}
    p = prepare(TRI, rels)
    want = got(baselines.brute(p.frames, ["a", "b", "c"]))
    for order in ("abc", "cba", "bca"):
        assert got(execute(p, "levels", list(order))) == want
    assert got(execute(p, "levels", driver="global")) == want
    assert got(execute(p, "cells", shares={"a": 2, "b": 3, "c": 1}, batch_rows=2)) == want
    assert got(run_split(TRI, rels, "b", 3)) == want
    r, s, t = (rels[n].toDF(*v).distinct() for n, v in (("R", "ab"), ("S", "bc"), ("T", "ac")))
    for tau in (0, 3, 10**6, None):
        assert got(baselines.heavy_light(r, s, t, tau)) == want
    assert got(baselines.pairwise_frames(p.frames, [2, 0, 1]).select("a", "b", "c")) == want
    assert costs.diff(execute(p, "levels"), execute(p, "hash")) == (0, 0)


def test_edges(spark):
    e, none = pairs(spark, [(1, 2), (2, 3), (1, 3)]), pairs(spark, [])
    for engine in ("levels", "cells", "broadcast", "pairwise"):
        for hole in "RST":
            rels = dict.fromkeys("RST", e) | {hole: none}
            assert got(run(TRI, rels, engine)) == []
    assert got(run("Q(x,y) :- E(x,y)", {"E": e})) == [(1, 2), (1, 3), (2, 3)]
    assert got(run("Q(x,z) :- A(x), B(z)", {"A": spark.range(2), "B": spark.range(2)})) == [(0, 0), (0, 1), (1, 0), (1, 1)]
    assert got(run("Q(x,y) :- E(x,y), E(x,y)", {"E": e})) == [(1, 2), (1, 3), (2, 3)]
    mixed = {"E": spark.createDataFrame([(1, 2)], "a int, b long"), "F": spark.createDataFrame([(2, 5)], "a long, b short")}
    assert got(run("Q(x,y,z) :- E(x,y), F(y,z)", mixed, "cells")) == [(1, 2, 5)]
    limits = pairs(spark, [(-(2**63), 2**63 - 1), (2**63 - 1, 0), (-(2**63), 0)])
    for engine in ("levels", "cells"):
        assert len(got(run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": limits}, engine))) == 1
    words = spark.createDataFrame([("ab", "abc"), ("abc", "a"), ("ab", "a")], "x string, y string")
    for engine in ("levels", "cells", "broadcast"):
        assert got(run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": words}, engine)) == [("ab", "abc", "a")]


def test_skewed_key(spark):
    e = pairs(spark, [(0, i) for i in range(300)] + [(i, i + 1) for i in range(300)])
    q = "Q(a,b,c) :- E(a,b), E(b,c), E(a,c)"
    want = got(run(q, {"E": e}))
    assert got(run_split(q, {"E": e}, "a", 50)) == want == got(run(q, {"E": e}, "cells"))


def test_heavy_values_are_found_and_split(spark):
    e = pairs(spark, [(0, i) for i in range(3000)] + [(i, i + 1) for i in range(3000)] + [(i, 0) for i in range(0, 3000, 3)])
    q = "Q(a,b,c) :- E(a,b), E(b,c), E(a,c)"
    p = prepare(q, {"E": e})
    frames = settle(p.frames)
    assert len({id(f.df) for f in frames}) == 3 and {f.rows for f in frames} == {e.distinct().count()}
    assert heavy_values(frames, {"a": 4, "b": 4, "c": 1}) == {"a": [0], "b": [0]}
    want = got(run(q, {"E": e}, "broadcast"))
    for skew in ("split", "off"):
        assert got(run(q, {"E": e}, "cells", skew=skew)) == want
        assert execute(p, "cells", measure="count", skew=skew).agg(F.sum("n")).first()[0] == len(want)


def test_counts_without_listing(spark):
    rng = random.Random(4)
    e = pairs(spark, [(rng.randint(0, 30), rng.randint(-5, 30)) for _ in range(300)])
    for q in ("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", "Q(a,b,c,d) :- E(a,b), E(b,c), E(c,d), E(a,d)", "Q(a,b,c) :- E(a,b), E(b,c)", "Q(a,b) :- E(a,b), E(b,a)"):
        n = run(q, {"E": e}).count()
        for engine in ("auto", "cells", "broadcast", "levels", "hash", "pairwise"):
            assert count(q, {"E": e}, engine=engine).first()[0] == n, (q, engine)
    assert count("Q(a,b,c) :- E(a,b), E(b,c), E(a,c), a < b", {"E": e}).first()[0] == run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c), a < b", {"E": e}).count()


def test_choices():
    tri, order = [("a", "b"), ("b", "c"), ("a", "c")], ["a", "b", "c"]
    assert choice.choose_engine(tri, [100] * 3, order, [1.0] * 3, 64)[0] == "broadcast"
    big = [10**9] * 3
    shares = choice.enough_cells(tri, big, order, 64)
    assert choice.cell_load(tri, big, shares) <= choice.CELL_BYTES < choice.cell_load(tri, big, choice.best_shares(tri, big, order, 64))
    assert choice.enough_cells(tri, [10**15] * 3, order, 64) is None
    few = [10.0] * 3
    assert choice.choose_engine(tri, [10**15] * 3, order, few, 64)[0] == "levels"
    assert choice.choose_engine(tri, [10**15, 10**12, 10**15], order, few, 64)[0] == "hash"
    assert choice.choose_engine(tri, [10**15, 10**12, 10**15], order, few, 64, sorted_already=True)[0] == "levels"
    assert choice.choose_engine(tri[:2], [10**9] * 2, order, few, 64)[0] == "pairwise"


def test_engines_read_kept_layouts(spark):
    cat = layout.LayoutCatalog(spark, "t_kept", 2)
    rng = random.Random(2)
    e = {"E": pairs(spark, [(rng.randint(0, 9), rng.randint(0, 9)) for _ in range(50)])}
    q = "Q(a,b,c) :- E(a,b), E(b,c), E(a,c)"
    want = got(run(q, e))
    assert got(run(q, e, "levels", layouts=cat)) == want == got(run(q, e, "cells", layouts=cat)) and len(cat.known) == 1
    # the kept table is what is read: rows added to it count without the relation being given again
    cat.refresh("E", pairs(spark, [(50, 51), (51, 52), (50, 52)]))
    assert got(run(q, e, "levels", layouts=cat)) == sorted([*want, (50, 51, 52)])
    cat.drop()


def test_products_without_a_common_variable(spark, monkeypatch):
    a, b = {"A": spark.range(7), "B": spark.range(5)}, sorted((x, y) for x in range(7) for y in range(5))
    assert got(run("Q(x,y) :- A(x), B(y)", a, "levels")) == b
    monkeypatch.setattr(level_engine, "BROADCAST_ROWS", 1)
    assert got(run("Q(x,y) :- A(x), B(y)", a, "levels")) == b


def test_golden_sizes(spark):
    assert W.w01(spark, SMALL).count() == 59
    assert W.w02(spark, SMALL).count() == 2615
    assert W.w02_count(spark, SMALL, "co_supp").first()[0] == 120
    assert W.w03(spark, SMALL).count() == 136 and W.w03_parts(spark, SMALL).count() == 34 and W.w04(spark, SMALL).count() == 0
    assert W.w20(spark, SMALL).count() == 139
    assert W.rule_on(spark, SMALL, "Q(a,b,c) :- E(a,b), E(b,c), not E(a,c)", {"E": "hop"}).count() == 241


def test_costs_and_certificate(spark):
    p = W.w01_prepared(spark, SMALL)
    assert [c for _, c, _ in costs.level_costs(p, ["a", "b", "c"])] == [150, 1444, 1444]
    assert costs.level_costs(p, ["c", "b", "a"]) == [("c", 10, 10), ("b", 10, 10), ("a", 62, 59)]
    cert = costs.certify(p, ["c", "b", "a"], moves=True)
    assert cert["ok"] and cert["bound"] == pytest.approx(1471.73, abs=0.01)
    assert dict((tuple(sorted("RST"[i] for i in t[:2])), n) for t, n in baselines.pairwise_all(p.frames)) == {("R", "S"): 1444, ("S", "T"): 62, ("R", "T"): 1444}


def test_cells_send_a_list_a_prefix(spark):
    """Python gives the last variable's values as lists, long ones in pieces; Spark makes them rows."""
    e = spark.range(40).toDF("u").crossJoin(spark.range(40).toDF("v")).where("u < v")
    for batch_rows in (3, 1 << 16):
        df = run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": e}, "cells", ["a", "b", "c"], batch_rows=batch_rows)
        assert "Generate explode(c" in df._jdf.queryExecution().toString()
        assert sorted(tuple(r) for r in df.collect()) == list(combinations(range(40), 3))


def test_counterexample(spark):
    inst = projection_instance(spark, 1)
    p = prepare(TRI, inst)
    assert [c for _, c, _ in costs.level_costs(p, ["a", "b", "c"])] == [8, 256, 256]
    rows = baselines.heavy_light_sweep(inst["R"], inst["S"].toDF("b", "c"), inst["T"].toDF("a", "c"), [8, 7]).collect()
    assert (rows[0]["light_rows"], rows[1]["product_rows"]) == (2048, 8192)
    linear, probes = costs.compare_density(p, ["a", "b", "c"])
    assert linear == 1031 and probes > 0


def test_grid_meets_its_bound(spark):
    g = grid(spark, 8)
    p = prepare(TRI, {"R": g, "S": g, "T": g})
    assert execute(p, "cells").count() == 512 and costs.certify(p, ["a", "b", "c"])["bound"] == pytest.approx(512)
    cost = run_cells(p.frames, ["a", "b", "c"], {"a": 2}, measure="costs").groupBy("level").agg(F.sum("cost").alias("c"))
    assert dict(got(cost)) == {0: 8, 1: 64, 2: 512}


def test_rows_of_a_cell_are_packed(spark):
    far = [np.array([-(1 << 63), 0, (1 << 63) - 1]), np.array([5, 5, 260]), np.array([-7, 70_000, 3])]
    value = pack(far)
    assert all((a == b).all() for a, b in zip(unpack(value, 3), far, strict=True)) and len(value) == 8 + 3 * 9 + 3 * (8 + 1 + 4)
    edges = [(i, i * i % 997) for i in range(10_000)]
    p = prepare(TRI, dict.fromkeys("RST", spark.createDataFrame(edges, "x long, y long").repartition(2)))
    order, shares = ["a", "b", "c"], {"a": 2, "b": 2, "c": 2}
    dealt = assign(p.frames, order, shares).collect()
    assert len(dealt) <= 3 * 8 * p.frames[0].df.rdd.getNumPartitions()  # before: 60,000, a row a copy
    for atom, f in enumerate(p.frames):
        (lack,) = set(order) - set(f.vars)
        at = 1 << order.index(lack)
        for side in (0, 1):
            mine = [r for r in dealt if r["atom"] == atom and bool(r["cell"] & at) == bool(side)]
            found = [x for r in mine for x in zip(*(c.tolist() for c in unpack(bytes(r["packed"]), 2)), strict=True)]
            assert sorted(found) == edges
    few = pairs(spark, [(-(1 << 62), 0), (0, 1 << 62), (-(1 << 62), 1 << 62), (0, 1)])
    rows = run_cells(prepare(TRI, dict.fromkeys("RST", few)).frames, order, shares)
    assert got(rows) == [(-(1 << 62), 0, 1 << 62)] and not any(f.nullable for f in rows.schema.fields)


def test_shared_orders_deal_lineitem_once(spark):
    for name, key in (("co_supp", "l_suppkey"), ("co_part", "l_partkey")):
        found, by_order = relation(spark, SMALL, name), {}
        plan = found._jdf.queryExecution().executedPlan().toString()
        dealt_by = re.findall(r"Exchange hashpartitioning\(([^)]*), \d+\)", plan)
        assert sum(d.startswith("l_orderkey") for d in dealt_by) == 2 and not any(d.startswith("l_orderkey") and "," in d for d in dealt_by)  # before: by the pair
        for o, k in load(spark, SMALL, "lineitem", ["l_orderkey", key]).collect():
            by_order.setdefault(o, set()).add(k)
        assert got(found) == sorted({p for ks in by_order.values() for p in combinations(sorted(ks), 2)})


def test_meets(spark):
    for how in ("range", "count", "semi"):
        assert got(skip_meet.skip_meet(density_instance(spark, 50)[:2], "x", how)) == [(i,) for i in range(50, 100)]
        assert got(skip_meet.skip_meet(density_instance(spark, 50), "x", how)) == []
    assert got(skip_meet.skip_meet(density_instance(spark, 50), "x", pruned=True)) == []
    twice = spark.createDataFrame([(1,), (1,), (None,)], "x long")
    assert got(skip_meet.skip_meet([twice], "x")) == [(1,)] and got(skip_meet.skip_meet([twice, twice], "x")) == [(1,)]


def test_renumbering(spark):
    rows = [(1, 3, 4), (1, 3, 5), (1, 4, 6), (1, 4, 8), (1, 4, 9), (1, 5, 2), (3, 5, 2)]
    t, order = spark.createDataFrame(rows, "x long, y long, z long"), ["x", "y", "z"]
    assert got(renumber.renumber(t, "z", order)) == [(1, 3, 0), (1, 3, 1), (1, 4, 0), (1, 4, 1), (1, 4, 2), (1, 5, 0), (3, 5, 0)]
    assert got(renumber.renumber(t, "y", order)) == [(1, 0, 0), (1, 1, 0), (1, 2, 0), (3, 0, 0)]
    assert got(renumber.renumber(t, "x", order)) == [(0, 0, 0), (1, 0, 0)]
    assert all(renumber.size_shrinks(t, v, order) and renumber.projections_shrink(t, v, order) for v in order)
    p = prepare(TRI, {"R": pairs(spark, [(7, 4)]), "S": pairs(spark, [(4, 1), (4, 4), (4, 5), (4, 9)]), "T": pairs(spark, [(7, 2), (7, 3), (7, 5)])})
    assert got(renumber.witness(p, ["a", "b", "c"], "c")) == [(7, 4, 0), (7, 4, 1), (7, 4, 2)]
    rng = random.Random(5)
    make = lambda: pairs(spark, [(rng.randint(0, 5), rng.randint(0, 5)) for _ in range(15)])
    p = prepare(TRI, {"R": make(), "S": make(), "T": make()})
    for i, (v, c, _) in enumerate(costs.level_costs(p, ["a", "b", "c"])):
        assert renumber.witness(p, ["a", "b", "c"], v).count() == c, i


def test_families(spark):
    inst = {n: df.toDF(*v) for (n, df), v in zip(projection_instance(spark, 1).items(), ("ab", "bc", "ac"), strict=True)}
    size = families.SizeFamily(dict.fromkeys("RST", 256))
    assert size.holds(inst) and size.largest_answer(dict(zip("RST", map(frozenset, ("ab", "bc", "ac")), strict=True))) == pytest.approx(4096)
    assert all(families.check_closure(size, inst, ["a", "b", "c"]).values())
    proj = families.ProjectionFamily({("R", ("a",)): 8, ("R", ("b",)): 32, ("T", ("c",)): 1})
    assert all(families.check_closure(proj, inst, ["a", "b", "c"]).values())
    assert not families.graph_family("R", 10).holds(inst)
    hop = relation(spark, SMALL, "hop")
    half = hop.where("u < 8")
    assert families.dominance_violations(half, hop, "u").count() == 0 and families.dominance_violations(hop, half, "u").count() > 0
    assert families.shape_embeds({(1, 2), (1, 3)}, {(5, 1), (6, 1), (6, 2), (6, 9)}) and not families.shape_embeds({(1, 2), (2, 2)}, {(5, 1), (5, 2)})
    assert families.PrototypeFamily({"R": {(0, 0), (0, 1)}}).holds_rows({"R": {(9, 4)}})


def test_existential_and_facade(spark):
    rels = W.w01_relations(spark, SMALL)
    assert run("Q(a) :- R(a,b), S(b,c), T(a,c)", rels).count() == 59
    assert exists(TRI, rels) and first(TRI, rels, 3).count() == 3
    e = {"E": relation(spark, SMALL, "hop")}
    assert count("Q(a,b,c) :- E(a,b), E(b,c)", e).first()[0] == 2856
    a = Answer(W.w01(spark, SMALL))
    assert a.prefix(1).count() <= a.prefix(2).count() <= 59
    some = a.df.first()
    assert (some["b"],) in got(a.children((some["a"],)))
    named = attach(a.df, load(spark, SMALL, "customer"), {"a": "c_custkey"}, ["c_name"])
    assert named.count() == 59 and "c_name" in named.columns
    text = explain(TRI, rels)
    assert "bound" in text and "level c" in text
    sql = baselines.to_sql(JoinQuery.of("a b", Atom("R", ("a", "b"))), {"R": ["x", "y"]})
    assert sql == "SELECT DISTINCT t0.x AS a, t0.y AS b FROM R t0"
    hidden = run("Q(a) :- E(a,b), b < 3", e)
    assert hidden.count() == e["E"].where("v < 3").select("u").distinct().count()


def test_dictionary_layout_and_limits(spark):
    words = spark.createDataFrame([("b",), ("a",), ("c",), ("a",), (None,)], "w string")
    assert got(encode_domain([(words, "w")])) == [("a", 0), ("b", 1), ("c", 2)]
    cat = layout.LayoutCatalog(spark, "t_layout", 2)
    rel = pairs(spark, [(1, 2), (3, 4)])
    assert cat.build("r", rel, ["y", "x"]).columns == ["y", "x"]
    cat.refresh("r", pairs(spark, [(1, 2), (5, 6)]))
    cat.compact("r")
    assert got(cat.build("r", rel, ["y", "x"])) == [(2, 1), (4, 3), (6, 5)]
    cat.drop()
    p = prepare(TRI, {"R": rel, "S": rel, "T": rel})
    with pytest.raises(TooLarge):
        run_broadcast(spark, p.frames, ["a", "b", "c"], most=1)
