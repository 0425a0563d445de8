"""The workloads over the given tables: each a rule over derived relations, to be run by any engine."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, costs, skip_meet
from .operators.engine import Prepared, count, prepare, run
from .plans.parse import rule
from .sources.scratch import cut
from .sources.tables import load, relation

TRIANGLE = "Q(a,b,c) :- R(a,b), S(b,c), T(a,c)"


def w01_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {"R": relation(spark, sf_dir, "cs"), "S": relation(spark, sf_dir, "sn"), "T": relation(spark, sf_dir, "cn")}


def longs(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    return df.select(*(F.col(c).cast("long").alias(c) for c in columns or df.columns))


def w01(spark: SparkSession, sf_dir: str, engine: str = "levels", order: list[str] | None = None, **kw) -> DataFrame:
    """Customers and suppliers of one nation that an order ties."""
    rels = w01_relations(spark, sf_dir)
    if engine == "heavy_light":
        r, s, t = (rels[n].toDF(*v) for n, v in (("R", "ab"), ("S", "bc"), ("T", "ac")))
        return longs(baselines.heavy_light(r, s.distinct(), t.distinct()))
    return longs(run(TRIANGLE, rels, engine, order, **kw), ["a", "b", "c"])


def w01_prepared(spark: SparkSession, sf_dir: str) -> Prepared:
    return prepare(TRIANGLE, w01_relations(spark, sf_dir))


def w02(spark: SparkSession, sf_dir: str, edges: str = "hop", engine: str = "levels", order: list[str] | None = None) -> DataFrame:
    """Triangles of one graph."""
    return longs(run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": relation(spark, sf_dir, edges)}, engine, order))


def w02_count(spark: SparkSession, sf_dir: str, edges: str) -> DataFrame:
    return count("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": relation(spark, sf_dir, edges)})


def w03_inputs(spark: SparkSession, sf_dir: str) -> list[DataFrame]:
    return [load(spark, sf_dir, "orders", ["o_custkey"], F.col("o_orderstatus") == s) for s in ("F", "O", "P")]


def w03(spark: SparkSession, sf_dir: str, how: str = "range") -> DataFrame:
    """Customers with orders of every status."""
    return skip_meet.skip_meet(w03_inputs(spark, sf_dir), "o_custkey", how)


def w03_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    small = [load(spark, sf_dir, "lineitem", ["l_partkey"], (F.col("l_returnflag") == s) & (F.col("l_quantity") < 5)) for s in ("A", "N", "R")]
    return skip_meet.skip_meet(small, "l_partkey")


def w04(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order keys in the lower two thirds, the upper two thirds and the outer thirds: any two share a third, all three nothing."""
    keys = load(spark, sf_dir, "orders", ["o_orderkey"])
    third = (keys.agg(F.max("o_orderkey")).first()[0] + 1) // 3
    k = F.col("o_orderkey")
    return skip_meet.skip_meet([keys.where(k < 2 * third), keys.where(k >= third), keys.where((k < third) | (k >= 2 * third))], "o_orderkey", pruned=True)


def prefix_counts(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Nodes of a relation's trie at each depth."""
    df = relation(spark, sf_dir, name)
    cols = df.columns
    row = df.agg(*(F.count_distinct(*cols[: d + 1]).alias(str(d + 1)) for d in range(len(cols))))
    return row.select(F.explode(F.array(*(F.struct(F.lit(d + 1).alias("depth"), F.col(str(d + 1)).alias("n")) for d in range(len(cols))))).alias("x")).select("x.*")


def w06(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sums of level costs of the triangle in all six orders."""
    return costs.all_order_costs(w01_prepared(spark, sf_dir))


def rule_on(spark: SparkSession, sf_dir: str, text: str, rels: dict[str, str], engine: str = "levels", order: list[str] | None = None) -> DataFrame:
    return run(rule(text), {k: relation(spark, sf_dir, v) for k, v in rels.items()}, engine, order)


def w20(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers of nations 1 to 3 or with a finished order, who also have an open-priced one."""
    orders = load(spark, sf_dir, "orders", ["o_custkey", "o_orderstatus"])
    near = load(spark, sf_dir, "customer", ["c_custkey"], F.col("c_nationkey").isin(1, 2, 3))
    return run("Q(x) :- P(x,'P'), (A(x) ; P(x,'F'))", {"P": orders, "A": near})


def w21_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    e = load(spark, sf_dir, "events", ["user_id", "event_type", "ts"])
    day1 = e.where(F.dayofmonth("ts") == 1)
    return {
        "Buys": day1.where(F.col("event_type").isin("purchase", "click")).select("user_id"),
        "Err": e.where("event_type = 'error'").select("user_id"),
        "Signed": e.where("event_type = 'signup'").select("user_id"),
        "H": relation(spark, sf_dir, "hop"),
    }


def w21(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with (a purchase or click on day 1, or a hop to a user with an error) and (a sign-up, or a triangle of hops)."""
    from .plans.ir import And, Atom, Exists, JoinQuery, Or

    hop_err = Exists(("y",), And((Atom("H", ("x", "y")), Atom("Err", ("y",)))))
    tri = Exists(("y", "z"), And((Atom("H", ("x", "y")), Atom("H", ("y", "z")), Atom("H", ("x", "z")))))
    q = JoinQuery.of("x", Or((Atom("Buys", ("x",)), hop_err)), Or((Atom("Signed", ("x",)), tri)))
    return run(q, w21_relations(spark, sf_dir))


def w25(spark: SparkSession, sf_dir: str, engine: str = "cells") -> DataFrame:
    """The first workload with names for keys."""
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_name", "c_nationkey"])
    s = load(spark, sf_dir, "supplier", ["s_suppkey", "s_name", "s_nationkey"])
    n = load(spark, sf_dir, "nation", ["n_nationkey", "n_name"])
    cs = relation(spark, sf_dir, "cs")
    r = cs.join(c, cs["o_custkey"] == c["c_custkey"]).join(s, cs["l_suppkey"] == s["s_suppkey"]).select("c_name", "s_name")
    sn = s.join(n, s["s_nationkey"] == n["n_nationkey"]).select("s_name", "n_name")
    cn = c.join(n, c["c_nationkey"] == n["n_nationkey"]).select("c_name", "n_name")
    return run(TRIANGLE, {"R": r, "S": sn, "T": cn}, engine)


def w28_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents", ["doc_id", "lang", "source"])
    return run("Q(d,l,s,q) :- D(d,l,s), Y(d,q)", {"D": d, "Y": load(spark, sf_dir, "labels", ["doc_id", "quality"])}, "pairwise")


def line_keys(spark: SparkSession, sf_dir: str, table: str, key: str) -> DataFrame:
    """(id, k): the trimmed lines of 40 characters or more of each text, as hashes."""
    lines = load(spark, sf_dir, table, [key, "text"]).select(F.col(key).alias("id"), F.explode(F.split("text", "\n")).alias("line")).select("id", F.trim("line").alias("line"))
    return lines.where(F.char_length("line") >= 40).select("id", F.sha2("line", 256).alias("k")).distinct()


def line_classes(keyed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(id, size) of each set of shared lines that documents have, named by its least document; and (id, k), its lines.

    Documents of one set have the same neighbours, so copies stand as one row with their number, however many there are.
    """
    often = keyed.groupBy("k").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("k")
    shared = cut(keyed.join(often, "k", "left_semi"), "shared-lines")
    signed = shared.groupBy("id").agg(F.sha2(F.concat_ws(",", F.sort_array(F.collect_list("k"))), 256).alias("lines"))
    classes = cut(signed.groupBy("lines").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("size")).select("id", "size"), "line-classes")
    return classes, shared.join(classes.select("id"), "id", "left_semi")


def shared_line_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row, n: triples of documents each two of which share a line. Pairs are made of classes alone; those within a class, and between
    two, are counted by their sizes."""
    classes, lines = line_classes(line_keys(spark, sf_dir, "documents", "doc_id"))
    other = lines.select(F.col("id").alias("v"), F.col("k").alias("k2"))
    edges = cut(lines.join(other, (F.col("k") == F.col("k2")) & (F.col("id") < F.col("v"))).select(F.col("id").alias("u"), "v").distinct(), "class-edges")
    named = lambda v: classes.select(F.col("id").alias(v), F.col("size").cast("decimal(38,0)").alias(f"s{v}"))
    pairs = lambda s: F.expr(f"{s} * ({s} - 1) / 2")
    one = named("a").agg(F.sum(F.expr("sa * (sa - 1) * (sa - 2) / 6")).alias("n"))
    two = edges.toDF("a", "b").join(named("a"), "a").join(named("b"), "b").agg(F.sum(pairs("sa") * F.col("sb") + pairs("sb") * F.col("sa")).alias("n"))
    three = run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": edges}, "auto").join(named("a"), "a").join(named("b"), "b").join(named("c"), "c").agg(F.sum(F.col("sa") * F.col("sb") * F.col("sc")).alias("n"))
    return one.union(two).union(three).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def benchmark_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items and documents that share a line: the line is a hidden variable of the rule."""
    rels = {"B": line_keys(spark, sf_dir, "benchmark", "item_id"), "D": line_keys(spark, sf_dir, "documents", "doc_id")}
    return run("Q(i,d) :- B(i,k), D(d,k)", rels, "pairwise").toDF("item_id", "doc_id")
