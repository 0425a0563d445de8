"""Every named query over the given tables, and the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable
from itertools import permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as W
from .functions import columns as C
from .kernel.cursor import OpCounter, SortedCursor
from .kernel.meet import SkipMeet, drain
from .operators import baselines, costs, families, renumber, surround
from .operators.cell_engine import run_cells
from .operators.engine import Prepared, count, prepare, run
from .operators.skip_meet import skip_meet
from .plans.bounds import cover_bound, growth_exponent, projection_bound
from .plans.rewrite import KeyFrame
from .sources.scratch import cut, fresh_path
from .sources.synthetic import grid_of, hub_of, projection_of, residues
from .sources.tables import load, relation
from .streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: SQL of the derived relations, columns as the rules name them.
RELATIONS = {
    "cs": "SELECT DISTINCT o_custkey AS a, l_suppkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "sn": "SELECT DISTINCT s_suppkey AS b, CAST(s_nationkey AS BIGINT) AS c FROM supplier",
    "cn": "SELECT DISTINCT c_custkey AS a, CAST(c_nationkey AS BIGINT) AS c FROM customer",
    "nn": "SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS u, CAST(s_nationkey AS BIGINT) AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey",
    "hop": "SELECT DISTINCT u, v FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL AND u <> v",
    "co_supp": "SELECT DISTINCT x.l_suppkey AS u, y.l_suppkey AS v FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_suppkey < y.l_suppkey",
    "co_part": "SELECT DISTINCT x.l_partkey AS u, y.l_partkey AS v FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "bts": "SELECT DISTINCT p_brand AS a, p_type AS b, p_size AS c FROM part",
    "utd": "SELECT DISTINCT user_id AS a, event_type AS b, day(ts) AS c FROM events",
    "zipf": "SELECT DISTINCT l_partkey % 400 * (l_partkey % 400) // 800 AS u, 2000 // (1 + l_suppkey * 7 % 200) AS v FROM lineitem",
}


def named(name: str, sql: str | None = None, needs: str = ""):
    """Registers a query; sql may use the derived relations named in needs."""

    def wrap(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql is not None:
            parts = ", ".join(f"{n} AS ({RELATIONS[n]})" for n in needs.split())
            ORACLES[name] = (f"WITH {parts} " if parts else "") + sql
        return f

    return wrap


def one_row(spark: SparkSession, schema: str, *values) -> DataFrame:
    return spark.createDataFrame([values], schema)


# --- triangles -------------------------------------------------------------------------------------------------------
TRI = "SELECT a, b, c FROM cs JOIN sn USING (b) JOIN cn USING (a, c)"
for _engine in ("cells", "levels", "hash", "broadcast", "pairwise", "heavy_light", "auto"):
    named(f"tri_same_nation_{_engine}", TRI, "cs sn cn")(lambda s, d, e=_engine: W.w01(s, d, e))
named("tri_same_nation_global_driver", TRI, "cs sn cn")(lambda s, d: W.w01(s, d, driver="global"))

HOP3 = "SELECT x.u AS a, x.v AS b, y.v AS c FROM {e} x JOIN {e} y ON x.v = y.u JOIN {e} z ON z.u = x.u AND z.v = y.v"
for _engine in ("cells", "levels", "hash"):
    named(f"tri_hop_{_engine}", HOP3.format(e="hop"), "hop")(lambda s, d, e=_engine: W.w02(s, d, "hop", e))
for _name, _edges in (("tri_hop_count", "hop"), ("tri_copart_count", "co_part"), ("tri_cosupp_count", "co_supp")):
    named(_name, f"SELECT count(*) AS n FROM ({HOP3.format(e=_edges)})", _edges)(lambda s, d, e=_edges: W.w02_count(s, d, e))
named("tri_cosupp", HOP3.format(e="co_supp"), "co_supp")(lambda s, d: W.w02(s, d, "co_supp", "cells"))
named("grid_nation_triangle", HOP3.format(e="nn"), "nn")(lambda s, d: W.w02(s, d, "nn", "cells"))


@named("skew_split_triangle", TRI, "cs sn cn")
def skew_split_triangle(s, d):
    """Heavy nations apart, by a threshold that the caller gives."""
    from .operators.engine import run_split

    return W.longs(run_split(W.TRIANGLE, W.w01_relations(s, d), "c", 500), ["a", "b", "c"])


for _skew in ("split", "off"):

    @named(f"tri_zipf_{_skew}", HOP3.format(e="zipf"), "zipf")
    def tri_zipf(s, d, k=_skew):
        """Triangles of a graph in which a few values hold most edges; split: these are found and joined apart by the engine itself."""
        return W.longs(run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": relation(s, d, "zipf")}, "cells", skew=k), ["a", "b", "c"])


@named("cycle4_nation_count", "SELECT count(*) AS n FROM nn p JOIN nn q ON p.v = q.u JOIN nn r ON q.v = r.u JOIN nn t ON r.v = t.u AND t.v = p.u", "nn")
def cycle4_nation_count(s, d):
    return count("Q(a,b,c,e) :- E(a,b), E(b,c), E(c,e), E(e,a)", {"E": relation(s, d, "nn")})


@named("clique4_nation_count", "SELECT count(*) AS n FROM nn p JOIN nn q ON p.u = q.u JOIN nn r ON p.u = r.u JOIN nn s ON s.u = p.v AND s.v = q.v JOIN nn t ON t.u = p.v AND t.v = r.v JOIN nn w ON w.u = q.v AND w.v = r.v", "nn")
def clique4_nation_count(s, d):
    return count("Q(a,b,c,e) :- E(a,b), E(a,c), E(a,e), E(b,c), E(b,e), E(c,e)", {"E": relation(s, d, "nn")})


@named("bowtie_hop_count", f"SELECT CAST(sum(k * k) AS BIGINT) AS n FROM (SELECT a, count(*) AS k FROM ({HOP3.format(e='hop')}) GROUP BY a)", "hop")
def bowtie_hop_count(s, d):
    """Two triangles that share their first corner: the halves are independent once it is bound, so counts multiply."""
    tri = W.w02(s, d, "hop").groupBy("a").agg(F.count(F.lit(1)).alias("k"))
    return tri.agg(F.sum(F.col("k") * F.col("k")).cast("long").alias("n"))


@named("bowtie_rule_count", f"SELECT CAST(sum(k * k) AS BIGINT) AS n FROM (SELECT a, count(*) AS k FROM ({HOP3.format(e='nn')}) GROUP BY a)", "nn")
def bowtie_rule_count(s, d):
    """The bow-tie as one rule of five variables, counted by the walk."""
    return count("Q(a,b,c,e,f) :- E(a,b), E(b,c), E(a,c), E(a,e), E(e,f), E(a,f)", {"E": relation(s, d, "nn")}, ["a", "b", "c", "e", "f"])


HUB = "p AS (SELECT DISTINCT l_partkey % 2000 + 1 AS i FROM lineitem), e AS (SELECT 0 AS u, i AS v FROM p UNION ALL SELECT i, 0 FROM p UNION ALL SELECT p.i, q.i FROM p JOIN p q ON q.i = p.i + 1)"
for _engine in ("auto", "cells", "pairwise"):

    @named(f"tri_hub_{_engine}", f"WITH {HUB} {HOP3.format(e='e')}")
    def tri_hub(s, d, k=_engine):
        """A graph with one hub, its spokes the parts of all lines modulo 2,000: binary plans pass through the square of its edges, whatever is
        reduced before; the walk does not."""
        spokes = residues(load(s, d, "lineitem", ["l_partkey"]), "l_partkey", 2000).select((F.col("x") + 1).alias("i"))
        return run("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": hub_of(spokes)}, k)


@named("pairs3_part", "SELECT x.a, x.b, y.c FROM (SELECT DISTINCT a, b FROM bts) x JOIN (SELECT DISTINCT b, c FROM bts) y ON x.b = y.b JOIN (SELECT DISTINCT a, c FROM bts) z ON z.a = x.a AND z.c = y.c", "bts")
def pairs3_part(s, d):
    t = relation(s, d, "bts").toDF("a", "b", "c")
    return run(W.TRIANGLE, {"R": t.select("a", "b"), "S": t.select("b", "c"), "T": t.select("a", "c")}, "cells")


# --- acyclic shapes, atoms of special form ----------------------------------------------------------------------------
@named("path_acyclic", "SELECT r_name, count(*) AS n FROM (SELECT DISTINCT r_name, n_nationkey, c_custkey, o_orderkey, l_linenumber FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey) GROUP BY r_name")
def path_acyclic(s, d):
    t = lambda n, *c: load(s, d, n, [*c])
    rels = {"Re": t("region", "r_regionkey", "r_name"), "Na": t("nation", "n_nationkey", "n_regionkey"), "Cu": t("customer", "c_custkey", "c_nationkey"), "Or": t("orders", "o_orderkey", "o_custkey"), "Li": t("lineitem", "l_orderkey", "l_linenumber")}
    df = run("Q(r,rn,n,c,o,l) :- Re(r,rn), Na(n,r), Cu(c,n), Or(o,c), Li(o,l)", rels, "pairwise")
    return df.groupBy(F.col("rn").alias("r_name")).agg(F.count(F.lit(1)).alias("n"))


@named("quad_lineitem", "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s, CAST(l_linenumber AS BIGINT) AS l FROM lineitem")
def quad_lineitem(s, d):
    df = run("Q(o,p,s,l) :- L(o,p,s,l)", {"L": load(s, d, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"])}, "pairwise")
    return W.longs(df)


@named("path2_hop", "SELECT x.u AS a, x.v AS b, y.v AS c FROM hop x JOIN hop y ON x.v = y.u", "hop")
def path2_hop(s, d):
    return W.rule_on(s, d, "Q(a,b,c) :- E(a,b), E(b,c)", {"E": "hop"})


@named("loop_atom", "SELECT DISTINCT l_partkey AS x FROM lineitem WHERE l_partkey = l_suppkey")
def loop_atom(s, d):
    return run("Q(x) :- L(x,x)", {"L": load(s, d, "lineitem", ["l_partkey", "l_suppkey"])})


@named("misordered_atom", "SELECT DISTINCT o_custkey AS a, l_suppkey AS b, CAST(s_nationkey AS BIGINT) AS c FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON s_suppkey = l_suppkey")
def misordered_atom(s, d):
    """U(c,b) used in the order a, b, c: the permuted columns are made on the way."""
    sup = load(s, d, "supplier", ["s_nationkey", "s_suppkey"])
    return W.longs(run("Q(a,b,c) :- R(a,b), U(c,b)", {"R": relation(s, d, "cs"), "U": sup}, order=["a", "b", "c"]))


@named("const_atom", "SELECT DISTINCT c_custkey AS x FROM customer WHERE c_nationkey = 2")
def const_atom(s, d):
    return run("Q(x) :- C(x,2)", {"C": relation(s, d, "cn")})


@named("const_events", "SELECT DISTINCT event_id AS e FROM events WHERE user_id = 1 AND event_type = 'purchase'")
def const_events(s, d):
    return run("Q(e) :- E(e,1,'purchase')", {"E": load(s, d, "events", ["event_id", "user_id", "event_type"])})


@named("union_atom", "SELECT o_custkey AS x FROM orders WHERE o_orderstatus = 'P' INTERSECT (SELECT c_custkey FROM customer WHERE c_nationkey IN (1, 2, 3) UNION SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')")
def union_atom(s, d):
    return W.w20(s, d)


@named(
    "nested_or_and",
    "SELECT x FROM (SELECT user_id AS x FROM events WHERE day(ts) = 1 AND event_type IN ('purchase', 'click') UNION SELECT u FROM hop WHERE v IN (SELECT user_id FROM events WHERE event_type = 'error')) "
    "INTERSECT (SELECT user_id FROM events WHERE event_type = 'signup' UNION SELECT x.u FROM hop x JOIN hop y ON x.v = y.u JOIN hop z ON z.u = x.u AND z.v = y.v)",
    "hop",
)
def nested_or_and(s, d):
    return W.w21(s, d)


@named("exists_same_nation", "SELECT DISTINCT a FROM cs JOIN sn USING (b) JOIN cn USING (a, c)", "cs sn cn")
def exists_same_nation(s, d):
    return run("Q(a) :- R(a,b), S(b,c), T(a,c)", W.w01_relations(s, d))


@named("open_wedges", "SELECT x.u AS a, x.v AS b, y.v AS c FROM hop x JOIN hop y ON x.v = y.u WHERE NOT EXISTS (SELECT 1 FROM hop z WHERE z.u = x.u AND z.v = y.v)", "hop")
def open_wedges(s, d):
    return W.rule_on(s, d, "Q(a,b,c) :- E(a,b), E(b,c), not E(a,c)", {"E": "hop"})


@named("compare_view", "SELECT x.u AS a, x.v AS b, y.v AS c FROM hop x JOIN hop y ON x.v = y.u WHERE x.u < x.v AND x.v < y.v", "hop")
def compare_view(s, d):
    return W.rule_on(s, d, "Q(a,b,c) :- E(a,b), E(b,c), a < b, b < c", {"E": "hop"})


@named("string_keys_triangle", "SELECT c_name AS a, s_name AS b, n_name AS c FROM (SELECT a, b, c FROM cs JOIN sn USING (b) JOIN cn USING (a, c)) JOIN customer ON c_custkey = a JOIN supplier ON s_suppkey = b JOIN nation ON n_nationkey = c", "cs sn cn")
def string_keys_triangle(s, d):
    return W.w25(s, d)


@named("docs_labels", "SELECT DISTINCT doc_id AS d, lang AS l, source AS s, quality AS q FROM documents JOIN labels USING (doc_id)")
def docs_labels(s, d):
    return W.w28_docs(s, d)


@named("conversation_roles", "SELECT DISTINCT conv_id AS c, role AS r, turn AS t FROM conversations")
def conversation_roles(s, d):
    return run("Q(c,r,t) :- V(c,r,t)", {"V": load(s, d, "conversations", ["conv_id", "role", "turn"])}, "pairwise")


@named("page_hosts", "SELECT DISTINCT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS h FROM pages")
def page_hosts(s, d):
    return run("Q(h) :- P(h,p)", {"P": load(s, d, "pages", ["url", "page_id"]).select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1), "page_id")})


@named("embedding_labels", "SELECT CAST(label AS BIGINT) AS l, count(*) AS n FROM embeddings GROUP BY label")
def embedding_labels(s, d):
    df = run("Q(l,v) :- E(v,l)", {"E": load(s, d, "embeddings", ["vec_id", "label"])}, "pairwise")
    return df.groupBy(F.col("l").cast("long").alias("l")).agg(F.count(F.lit(1)).alias("n"))


LINES = "k AS (SELECT DISTINCT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 40), e AS (SELECT DISTINCT x.doc_id AS u, y.doc_id AS v FROM k x JOIN k y ON x.line = y.line AND x.doc_id < y.doc_id)"


@named("shared_line_triangles", f"WITH {LINES} SELECT count(*) AS n FROM ({HOP3.format(e='e')})")
def shared_line_triangles(s, d):
    """Triangles of documents that share a line: clusters of copies."""
    return W.shared_line_triangles(s, d)


@named(
    "benchmark_lines",
    "SELECT DISTINCT item_id, doc_id FROM (SELECT item_id, trim(line, ' ') AS line FROM (SELECT item_id, unnest(string_split(text, chr(10))) AS line FROM benchmark)) JOIN (SELECT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) USING (line) WHERE length(line) >= 40",
)
def benchmark_lines(s, d):
    return W.benchmark_lines(s, d)


# --- unary meets ---------------------------------------------------------------------------------------------------------
STATUS = "SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'P'"
for _name, _how in (("meet_status_customers", "range"), ("meet_count_engine", "count"), ("meet_semi_engine", "semi")):
    named(_name, STATUS)(lambda s, d, h=_how: W.w03(s, d, h))
named("meet_pairwise", STATUS)(lambda s, d: baselines.pairwise_meet(W.w03_inputs(s, d), "o_custkey"))
named("meet_sort_merge", "SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")(lambda s, d: baselines.sort_merge(*W.w03_inputs(s, d)[:2], "o_custkey"))
named("meet_returnflag_parts", " INTERSECT ".join(f"SELECT l_partkey FROM lineitem WHERE l_returnflag = '{x}' AND l_quantity < 5" for x in "ANR"))(lambda s, d: W.w03_parts(s, d))
named("meet_disjoint_ranges", "SELECT o_orderkey FROM orders WHERE o_orderkey < 0")(lambda s, d: W.w04(s, d))
named("meet_pruned", "SELECT o_custkey FROM orders WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O' INTERSECT SELECT o_custkey FROM orders WHERE o_orderstatus = 'P'")(lambda s, d: skip_meet(W.w03_inputs(s, d), "o_custkey", "range", pruned=True))


# --- tries and measures -----------------------------------------------------------------------------------------------------
@named("trie_prefixes_part", "SELECT 1 AS depth, count(DISTINCT a) AS n FROM bts UNION ALL SELECT 2, count(DISTINCT (a, b)) FROM bts UNION ALL SELECT 3, count(*) FROM bts", "bts")
def trie_prefixes_part(s, d):
    return W.prefix_counts(s, d, "bts")


@named("trie_prefixes_events", "SELECT 1 AS depth, count(DISTINCT a) AS n FROM utd UNION ALL SELECT 2, count(DISTINCT (a, b)) FROM utd UNION ALL SELECT 3, count(*) FROM utd", "utd")
def trie_prefixes_events(s, d):
    return W.prefix_counts(s, d, "utd")


LEVELS_ABC = (
    "q1 AS (SELECT DISTINCT a FROM cs SEMI JOIN cn USING (a)), q2 AS (SELECT a, b FROM cs SEMI JOIN q1 USING (a) SEMI JOIN sn USING (b)), "
    "da AS (SELECT a, count(DISTINCT b) AS k FROM cs GROUP BY a), ea AS (SELECT a, count(*) AS k FROM cn GROUP BY a), db AS (SELECT b, count(*) AS k FROM sn GROUP BY b), "
    "c0 AS (SELECT least((SELECT count(DISTINCT a) FROM cs), (SELECT count(DISTINCT a) FROM cn)) AS c), "
    "c1 AS (SELECT CAST(sum(least(k, (SELECT count(DISTINCT b) FROM sn))) AS BIGINT) AS c FROM q1 JOIN da USING (a)), "
    "c2 AS (SELECT CAST(sum(least(ea.k, db.k)) AS BIGINT) AS c FROM q2 JOIN ea USING (a) JOIN db USING (b))"
)
ORACLE_LEVELS = f"WITH {{}}, {LEVELS_ABC} SELECT 0 AS level, 'a' AS var, (SELECT c FROM c0) AS c, (SELECT count(*) FROM q1) AS n_rows UNION ALL SELECT 1, 'b', (SELECT c FROM c1), (SELECT count(*) FROM q2) UNION ALL SELECT 2, 'c', (SELECT c FROM c2), (SELECT count(*) FROM ({TRI}))"
CTE3 = ", ".join(f"{n} AS ({RELATIONS[n]})" for n in ("cs", "sn", "cn"))


@named("level_costs_tri", ORACLE_LEVELS.format(CTE3))
def level_costs_tri(s, d):
    return costs.costs_frame(W.w01_prepared(s, d), ["a", "b", "c"])


@named("prefix_sizes_tri", f"WITH {CTE3}, {LEVELS_ABC} SELECT 'a' AS var, (SELECT count(*) FROM q1) AS n_rows UNION ALL SELECT 'b', (SELECT count(*) FROM q2) UNION ALL SELECT 'c', (SELECT count(*) FROM ({TRI}))")
def prefix_sizes_tri(s, d):
    return costs.costs_frame(W.w01_prepared(s, d), ["a", "b", "c"]).select("var", "n_rows")


def _order_sql() -> str:
    """Sums of level costs of the triangle in each of the six orders, one SELECT an order: prefixes, then the least degree of each."""
    rels = {"cs": "ab", "sn": "bc", "cn": "ac"}
    out = []
    for order in permutations("abc"):
        x, y, z = order
        has = lambda *vs: [r for r, cols in rels.items() if set(vs) <= set(cols)]
        first = " INTERSECT ".join(f"SELECT {x} FROM {r}" for r in has(x))
        least_first = ", ".join(f"(SELECT count(DISTINCT {x}) FROM {r})" for r in has(x))
        (both,), (free,) = has(x, y), [r for r in has(y) if r not in has(x, y)]
        second = f"SELECT {x}, {y} FROM {both} SEMI JOIN ({first}) USING ({x}) SEMI JOIN {free} USING ({y})"
        c2 = f"(SELECT sum(least(k, (SELECT count(DISTINCT {y}) FROM {free}))) FROM ({first}) JOIN (SELECT {x}, count(*) AS k FROM {both} GROUP BY {x}) USING ({x}))"
        (rx,), (ry,) = has(x, z), has(y, z)
        c3 = f"(SELECT sum(least(kx, ky)) FROM ({second}) JOIN (SELECT {x}, count(*) AS kx FROM {rx} GROUP BY {x}) USING ({x}) JOIN (SELECT {y}, count(*) AS ky FROM {ry} GROUP BY {y}) USING ({y}))"
        out.append(f"SELECT '{','.join(order)}' AS variable_order, CAST(least({least_first}) + coalesce({c2}, 0) + coalesce({c3}, 0) AS BIGINT) AS total")
    return " UNION ALL ".join(out)


@named("order_costs_all", _order_sql(), "cs sn cn")
def order_costs_all(s, d):
    return W.w06(s, d)


@named(
    "cover_bound_tri",
    f"WITH {CTE3}, z AS (SELECT (SELECT count(*) FROM cs) AS r, (SELECT count(*) FROM sn) AS s, (SELECT count(*) FROM cn) AS t) "
    "SELECT round(least(sqrt(CAST(r AS DOUBLE) * s * t), CAST(r AS DOUBLE) * s, CAST(s AS DOUBLE) * t, CAST(r AS DOUBLE) * t), 2) AS bound FROM z",
)
def cover_bound_tri(s, d):
    p = W.w01_prepared(s, d)
    return one_row(s, "bound double", round(cover_bound(p.edges, [f.df.count() for f in p.frames])[0], 2))


@named("projection_stats", "SELECT count(*) AS n, count(DISTINCT a) AS n_a, count(DISTINCT b) AS n_b FROM cs", "cs")
def projection_stats(s, d):
    df = relation(s, d, "cs").toDF("a", "b")
    return df.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("a").alias("n_a"), F.count_distinct("b").alias("n_b"))


@named(
    "projection_bound_tri",
    f"WITH {CTE3}, z AS (SELECT CAST((SELECT count(*) FROM cs) AS DOUBLE) AS r, (SELECT count(*) FROM sn) AS s, (SELECT count(*) FROM cn) AS t, "
    "least((SELECT count(DISTINCT a) FROM cs), (SELECT count(DISTINCT a) FROM cn)) AS a, least((SELECT count(DISTINCT b) FROM cs), (SELECT count(DISTINCT b) FROM sn)) AS b, least((SELECT count(DISTINCT c) FROM sn), (SELECT count(DISTINCT c) FROM cn)) AS c) "
    "SELECT round(least(sqrt(r * s * t), r * s, s * t, r * t, r * c, s * a, t * b, CAST(a AS DOUBLE) * b * c), 2) AS bound FROM z",
)
def projection_bound_tri(s, d):
    p = W.w01_prepared(s, d)
    sizes, small = [], {}
    for f in p.frames:
        row = f.df.agg(F.count(F.lit(1)).alias("n"), *(F.count_distinct(v).alias(v) for v in f.vars)).first()
        sizes.append(row["n"])
        for v in f.vars:
            k = frozenset([v])
            small[k] = min(row[v], small.get(k, row[v]))
    return one_row(s, "bound double", round(projection_bound(p.edges, sizes, small), 2))


@named("intermediate_rows_tri", "SELECT 'R,S' AS pair, count(*) AS n FROM cs JOIN sn USING (b) UNION ALL SELECT 'S,T', count(*) FROM sn JOIN cn USING (c) UNION ALL SELECT 'R,T', count(*) FROM cs JOIN cn USING (a)", "cs sn cn")
def intermediate_rows_tri(s, d):
    names = "RST"
    rows = [(",".join(sorted(names[i] for i in t[:2])), n) for t, n in baselines.pairwise_all(W.w01_prepared(s, d).frames)]
    return s.createDataFrame(rows, "pair string, n long")


@named(
    "heavy_light_sweep",
    "SELECT CAST(tau AS DOUBLE) AS tau, (SELECT count(*) FROM (SELECT b FROM cs GROUP BY b HAVING count(*) > tau)) AS heavy, (SELECT count(*) FROM (SELECT b FROM cs GROUP BY b HAVING count(*) > tau)) * (SELECT count(*) FROM cn) AS product_rows, "
    "(SELECT count(*) FROM cs JOIN sn USING (b) WHERE b NOT IN (SELECT b FROM cs GROUP BY b HAVING count(*) > tau)) AS light_rows FROM (VALUES (0), (150), (500), (1000000000)) t(tau)",
    "cs sn cn",
)
def heavy_light_sweep(s, d):
    r = W.w01_relations(s, d)
    return baselines.heavy_light_sweep(r["R"].toDF("a", "b"), W.longs(r["S"].toDF("b", "c")).distinct(), W.longs(r["T"].toDF("a", "c")).distinct(), [0, 150, 500, 1_000_000_000])


@named(
    "certificate_tri",
    f"WITH {CTE3}, {LEVELS_ABC}, z AS (SELECT CAST((SELECT count(*) FROM cs) AS DOUBLE) AS r, (SELECT count(*) FROM sn) AS s, (SELECT count(*) FROM cn) AS t), "
    "q AS (SELECT least(sqrt(r * s * t), r * s, s * t, r * t) AS bound FROM z) "
    "SELECT 'a' AS var, c, (SELECT count(*) FROM q1) <= c AND c <= bound AS ok FROM c0, q UNION ALL SELECT 'b', c, (SELECT count(*) FROM q2) <= c AND c <= bound FROM c1, q "
    f"UNION ALL SELECT 'c', c, (SELECT count(*) FROM ({TRI})) <= c AND c <= bound FROM c2, q",
)
def certificate_tri(s, d):
    cert = costs.certify(W.w01_prepared(s, d), ["a", "b", "c"])
    return s.createDataFrame([(v, c, n <= c <= cert["bound"]) for v, c, n in cert["levels"]], "var string, c long, ok boolean")


# --- proof machinery, families ------------------------------------------------------------------------------------------------
RENUMBERED = {
    "brand": "SELECT DISTINCT dense_rank() OVER (ORDER BY a) - 1 AS a, CAST(0 AS BIGINT) AS b, CAST(0 AS BIGINT) AS c FROM bts",
    "type": "SELECT DISTINCT a, dense_rank() OVER (PARTITION BY a ORDER BY b) - 1 AS b, CAST(0 AS BIGINT) AS c FROM bts",
    "size": "SELECT DISTINCT a, b, dense_rank() OVER (PARTITION BY a, b ORDER BY c) - 1 AS c FROM bts",
}
for _name, _var in (("brand", "a"), ("type", "b"), ("size", "c")):
    named(f"renumber_part_{_name}", RENUMBERED[_name], "bts")(lambda s, d, v=_var: renumber.renumber(relation(s, d, "bts").toDF("a", "b", "c"), v, ["a", "b", "c"]))


@named("renumber_witness_tri", f"WITH {CTE3}, {LEVELS_ABC} SELECT (SELECT c FROM c2) AS n")
def renumber_witness_tri(s, d):
    return renumber.witness(W.w01_prepared(s, d), ["a", "b", "c"], "c").agg(F.count(F.lit(1)).alias("n"))


@named("degree_profile_hop", "SELECT row_number() OVER (ORDER BY k DESC) - 1 AS rank, k AS degree FROM (SELECT u, count(*) AS k FROM hop GROUP BY u)", "hop")
def degree_profile_hop(s, d):
    return W.longs(families.degree_profile(relation(s, d, "hop"), "u"))


RANKED = "{n} AS (SELECT row_number() OVER (ORDER BY k DESC) - 1 AS rank, k FROM (SELECT u, count(*) AS k FROM hop {where} GROUP BY u))"
DOMINANCE = ", ".join(["hop AS (" + RELATIONS["hop"] + ")", RANKED.format(n="whole", where=""), RANKED.format(n="half", where="WHERE u < (SELECT (max(u) + 1) // 2 FROM hop)")])


@named(
    "degree_dominance_hop",
    f"WITH {DOMINANCE} SELECT 'half in whole' AS direction, count(*) AS violations FROM half LEFT JOIN whole USING (rank) WHERE whole.k IS NULL OR half.k > whole.k "
    "UNION ALL SELECT 'whole in half', count(*) FROM whole LEFT JOIN half USING (rank) WHERE half.k IS NULL OR whole.k > half.k",
)
def degree_dominance_hop(s, d):
    """Hops from the lower half of the users embed in all hops, so no rank is exceeded; the other way round ranks are missing."""
    hop = cut(relation(s, d, "hop"), "hop")
    half = hop.where(F.col("u") < (hop.agg(F.max("u")).first()[0] + 1) // 2)
    both = [(n, families.dominance_violations(a, b, "u")) for n, a, b in (("half in whole", half, hop), ("whole in half", hop, half))]
    one, two = (df.agg(F.count(F.lit(1)).alias("violations")).select(F.lit(n).alias("direction"), "violations") for n, df in both)
    return one.unionByName(two)


@named("match_length_part", "SELECT p_partkey, CASE WHEN p_brand <> 'Brand#11' THEN 0 WHEN p_size <> 10 THEN 1 ELSE 2 END AS m FROM part")
def match_length_part(s, d):
    df = load(s, d, "part", ["p_partkey", "p_brand", "p_size"]).withColumns({"x": F.lit("Brand#11"), "y": F.lit(10)})
    return families.match_length(df, ["p_brand", "p_size"], ["x", "y"], "m").select("p_partkey", "m")


def projection_sql(j: int) -> str:
    """The projection family's relations for n = 2^(8j), of the suppliers and parts of all lines."""
    few, many = 1 << 3 * j, 1 << 5 * j
    return (
        f"few AS (SELECT DISTINCT l_suppkey % {few} AS x FROM lineitem), many AS (SELECT DISTINCT l_partkey % {many} AS x FROM lineitem), cs AS (SELECT f.x AS a, m.x AS b FROM few f, many m), "
        f"sn AS (SELECT m.x AS b, f.x AS c FROM few f, many m), cn AS (SELECT f.x * {many} + m.x AS a, 0 AS c FROM few f, many m)"
    )


SWEPT = {1: (0, 4, 7, 8, 16, 256), 2: (0, 32, 63, 64, 128, 65536)}


def _projection(s, d, j: int) -> dict[str, DataFrame]:
    return projection_of(load(s, d, "lineitem", ["l_suppkey", "l_partkey"]), j)


def _swept(inst: dict[str, DataFrame], j: int) -> DataFrame:
    return baselines.heavy_light_sweep(inst["R"], inst["S"].toDF("b", "c"), inst["T"].toDF("a", "c"), list(SWEPT[j]))


def _walk_cost(s, rels: dict[str, DataFrame]) -> int:
    """Sum of level costs, gathered by the walk itself in one job over cells of the first variable."""
    p = prepare(W.TRIANGLE, rels)
    return run_cells(p.frames, ["a", "b", "c"], {"a": 8}, measure="costs").agg(F.sum("cost")).first()[0]


for _j in (1, 2):

    @named(
        f"counterexample_{1 << 8 * _j}",
        f"WITH {projection_sql(_j)}, {LEVELS_ABC} SELECT (SELECT count(*) FROM ({TRI})) AS n_answers, (SELECT count(*) FROM cs JOIN sn USING (b)) AS light_rows, "
        "(SELECT count(DISTINCT b) FROM cs) * (SELECT count(*) FROM cn) AS product_rows, (SELECT c0.c + c1.c + c2.c FROM c0, c1, c2) AS walk_cost",
    )
    def counterexample(s, d, j=_j):
        """The projection family: the walk's cost against the heavy/light baseline's intermediates, the least and the most of all thresholds."""
        inst = _projection(s, d, j)
        sweep = _swept(inst, j).collect()
        least, most = min(r["light_rows"] + r["product_rows"] for r in sweep), max(r["product_rows"] for r in sweep)
        return one_row(s, "n_answers long, light_rows long, product_rows long, walk_cost long", run(W.TRIANGLE, inst, "auto").count(), least, most, _walk_cost(s, inst))

    @named(
        f"counterexample_sweep_{1 << 8 * _j}",
        f"WITH {projection_sql(_j)}, k AS (SELECT b, count(*) AS n FROM cs GROUP BY b), l AS (SELECT b, count(*) AS m FROM sn GROUP BY b) "
        "SELECT CAST(tau AS DOUBLE) AS tau, (SELECT count(*) FROM k WHERE n > tau) AS heavy, (SELECT count(*) FROM k WHERE n > tau) * (SELECT count(*) FROM cn) AS product_rows, "
        f"CAST((SELECT coalesce(sum(n * m), 0) FROM k JOIN l USING (b) WHERE n <= tau) AS BIGINT) AS light_rows FROM (VALUES {', '.join(f'({t})' for t in SWEPT[_j])}) t(tau)",
    )
    def counterexample_sweep(s, d, j=_j):
        return _swept(_projection(s, d, j), j)


GROWN = "SELECT family, measure, round(regr_slope(log2(y), log2(n)), 3) AS exponent FROM points GROUP BY family, measure"
GRIDS = (16, 32, 64)
LEVEL_SUM = "(SELECT c0.c + c1.c + c2.c FROM c0, c1, c2)"
_POINTS = " UNION ALL ".join(f"SELECT 'grid' AS family, 'walk cost' AS measure, {m * m} AS n, (SELECT count(DISTINCT a) + count(*) + (SELECT count(*) FROM g{m} x JOIN g{m} y ON x.b = y.a) FROM g{m}) AS y" for m in GRIDS)
_POINTS += "".join(
    f" UNION ALL SELECT 'projection', '{what}', {1 << 8 * j}, (WITH {projection_sql(j)}, {LEVELS_ABC} {sql})"
    for j in (1, 2)
    for what, sql in (("walk cost", f"SELECT * FROM {LEVEL_SUM}"), ("light rows", "SELECT count(*) FROM cs JOIN sn USING (b)"), ("product rows", "SELECT (SELECT count(DISTINCT b) FROM cs) * (SELECT count(*) FROM cn)"))
)


@named("growth_tri", "WITH " + ", ".join(f"r{m} AS (SELECT DISTINCT l_partkey % {m} AS x FROM lineitem), g{m} AS (SELECT p.x AS a, q.x AS b FROM r{m} p, r{m} q)" for m in GRIDS) + f", points AS ({_POINTS}) {GROWN}")
def growth_tri(s, d):
    """How costs grow with n, as exponents: the walk on grids, and the walk and both sides of heavy/light on the projection family."""
    parts = load(s, d, "lineitem", ["l_partkey"])
    points = {("grid", "walk cost"): [(m * m, _walk_cost(s, dict.fromkeys("RST", grid_of(parts, "l_partkey", m)))) for m in GRIDS]}
    for j in (1, 2):
        inst, n = _projection(s, d, j), 1 << 8 * j
        sweep = _swept(inst, j).collect()
        found = {"walk cost": _walk_cost(s, inst), "light rows": max(r["light_rows"] for r in sweep), "product rows": max(r["product_rows"] for r in sweep)}
        for what, y in found.items():
            points.setdefault(("projection", what), []).append((n, y))
    return s.createDataFrame([(*k, round(growth_exponent(p), 3)) for k, p in points.items()], "family string, measure string, exponent double")


_GRID = "g AS (SELECT u, v FROM nn), ga AS (SELECT u, count(*) AS k FROM g GROUP BY u)"


@named(
    "density_counters",
    f"WITH {CTE3}, nn AS ({RELATIONS['nn']}), {LEVELS_ABC}, {_GRID} "
    f"SELECT 'same nation' AS workload, (SELECT count(*) FROM ({TRI})) AS answers, (SELECT CAST(c0.c + c1.c + c2.c AS BIGINT) FROM c0, c1, c2) AS probes UNION ALL "
    "SELECT 'nations grid', (SELECT count(*) FROM g x JOIN g y ON x.v = y.u JOIN g z ON z.u = x.u AND z.v = y.v), "
    "(SELECT CAST((SELECT count(*) FROM ga) + (SELECT sum(least(k, (SELECT count(*) FROM ga))) FROM ga) + (SELECT sum(least(x.k, y.k)) FROM g JOIN ga x ON x.u = g.u JOIN ga y ON y.u = g.v) AS BIGINT))",
)
def density_counters(s, d):
    """Answers and probes of the hash walk: on W01 and on the grid. Two relations meet at every level, so each value of the smaller slice is
    one probe and probes are the level costs, which the hashed walk by levels sums over all executors."""
    rows = []
    for name, p in (("same nation", W.w01_prepared(s, d)), ("nations grid", prepare("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": relation(s, d, "nn")}))):
        levels = costs.level_costs(p, ["a", "b", "c"], "hash")
        rows.append((name, levels[-1][2], sum(c for _, c, _ in levels)))
    return s.createDataFrame(rows, "workload string, answers long, probes long")


DENSITY = (4, 100, 10000)


@named(
    "density_ops",
    f"WITH k AS (SELECT DISTINCT n, (7 * l_orderkey + l_linenumber) * 3001 % (3 * n) AS x FROM lineitem, (VALUES {', '.join(f'({n})' for n in DENSITY)}) t(n)) "
    "SELECT n, (SELECT count(*) + 1 FROM (VALUES (1), (2), (3))) AS skips, count(*) FILTER (x >= n AND x < 2 * n) AS pair_keys, count(*) FILTER (x < 2 * n AND x >= n AND (x < n OR x >= 2 * n)) AS answers FROM k GROUP BY n",
)
def density_ops(s, d):
    """Skips until the empty meet of the density example is known, one more than there are inputs whatever n, against the keys that a meet of two
    gives. The keys are those of all lines, modulo 3n, so at most 3n come to the driver, whose cursors count."""
    key = (F.col("l_orderkey") * 7 + F.col("l_linenumber")) * 3001
    made = F.explode(F.array(*(F.struct(F.lit(n).alias("n"), F.pmod(key, F.lit(3 * n)).alias("x")) for n in DENSITY))).alias("k")
    keys: dict[int, list[int]] = {n: [] for n in DENSITY}
    for r in load(s, d, "lineitem", ["l_orderkey", "l_linenumber"]).select(made).select("k.*").distinct().collect():
        keys[r["n"]].append(r["x"])
    rows = []
    for n in DENSITY:
        ops, all_ = OpCounter(), sorted(keys[n])
        sets = ([x for x in all_ if x < 2 * n], [x for x in all_ if x >= n], [x for x in all_ if x < n or x >= 2 * n])
        found = drain(SkipMeet([SortedCursor(x, ops) for x in sets]))
        rows.append((n, ops.total("skip"), len(drain(SkipMeet([SortedCursor(x, OpCounter()) for x in sets[:2]]))), len(found)))
    return s.createDataFrame(rows, "n int, skips long, pair_keys long, answers long")


@named("op_counts")
def op_counts(s, d):
    """Moves of the scalar walk and probes of the hash walk on the nations' grid."""
    p = prepare("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", {"E": relation(s, d, "nn")})
    return costs.ops_frame(p, ["a", "b", "c"])


@named("unary_trace", "SELECT * FROM (VALUES (1, 'A', 'skip', 2, 3), (2, 'B', 'skip', 3, 6), (3, 'C', 'skip', 6, 8), (4, 'A', 'skip', 8, 8), (5, 'B', 'skip', 8, 8), (6, 'C', 'step', -1, 10), (7, 'A', 'skip', 10, 11), (8, 'B', 'skip', 11, -1)) t(move, who, kind, target, landed) WHERE (SELECT count(DISTINCT l_partkey % 12) FROM lineitem) = 12")
def unary_trace(s, d):
    """The moves of the published example. Its sets are drawn from the parts of all lines modulo 12, every value of which it needs."""
    ops = OpCounter(trace=True)
    there = sorted(r["x"] for r in residues(load(s, d, "lineitem", ["l_partkey"]), "l_partkey", 12).collect())
    sets = ("A", {0, 1, 3, 4, 5, 6, 7, 8, 9, 11}), ("B", {0, 2, 6, 7, 8, 9}), ("C", {2, 4, 5, 8, 10})
    if len(there) < 12:
        return s.createDataFrame([], "move int, who string, kind string, target int, landed int")
    drain(SkipMeet([SortedCursor([x for x in there if x in keys], ops, name) for name, keys in sets]))
    return s.createDataFrame([(i, *(-1 if v is None else v for v in x)) for i, x in enumerate(ops.log, 1)], "move int, who string, kind string, target int, landed int")


# --- operators around the joins ----------------------------------------------------------------------------------------------
@named("filter_lineitem", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_shipdate IS NOT NULL")
def filter_lineitem(s, d):
    df = load(s, d, "lineitem")
    return surround.filtered(df, F.col("l_quantity").between(10, 20), F.col("l_returnflag").isin("A", "R"), F.col("l_shipdate").isNotNull()).select("l_orderkey", "l_linenumber")


SEGMENTS = "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"
for _algo in ("hash", "merge", "broadcast"):

    @named(f"join_{_algo}", SEGMENTS)
    def join_algo(s, d, a=_algo):
        o, c = load(s, d, "orders", ["o_custkey"]), load(s, d, "customer", ["c_custkey", "c_mktsegment"])
        return surround.equi_join(o, c, o["o_custkey"] == c["c_custkey"], "inner", a).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@named("join_theta", "SELECT count(*) AS n FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def join_theta(s, d):
    a = load(s, d, "supplier", ["s_nationkey", "s_acctbal"])
    b = a.toDF("n2", "bal2")
    return surround.theta_join(a, b, (F.col("s_nationkey") == F.col("n2")) & (F.col("s_acctbal") < F.col("bal2"))).agg(F.count(F.lit(1)).alias("n"))


@named("join_full_outer", "SELECT CAST(coalesce(x.k, y.k) AS BIGINT) AS k, coalesce(x.n, 0) AS suppliers, coalesce(y.n, 0) AS customers FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) x FULL JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) y ON x.k = y.k")
def join_full_outer(s, d):
    a = load(s, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    b = load(s, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    return surround.outer_join(a, b, "k").select(F.col("k").cast("long").alias("k"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"), F.coalesce("customers", F.lit(0)).alias("customers"))


@named("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def join_semi(s, d):
    return surround.semi(load(s, d, "customer", ["c_custkey"]), load(s, d, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"))


@named("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def join_anti(s, d):
    return surround.anti(load(s, d, "customer", ["c_custkey"]), load(s, d, "orders", ["o_custkey"]), F.col("c_custkey") == F.col("o_custkey"))


@named("range_join_ship", "SELECT o_orderkey, l_linenumber, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey AND epoch(l_shipdate)::BIGINT // 86400 >= epoch(o_orderdate)::BIGINT // 86400 AND epoch(l_shipdate)::BIGINT // 86400 < epoch(o_orderdate)::BIGINT // 86400 + 30")
def range_join_ship(s, d):
    """Lines shipped within 30 days of their order's date."""
    day = lambda c: (F.unix_timestamp(c) / 86400).cast("long")
    p = load(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_linenumber", "l_partkey", day("l_shipdate").alias("x"))
    o = load(s, d, "orders").select("o_orderkey", day("o_orderdate").alias("lo")).withColumn("hi", F.col("lo") + 30)
    return surround.range_join(p, o, "x", "lo", "hi", 30, ["o_orderkey"]).select("o_orderkey", "l_linenumber", "l_partkey")


@named("asof_events", "SELECT p.event_id, coalesce(v.event_id, -1) AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def asof_events(s, d):
    e = load(s, d, "events", ["event_id", "user_id", "ts", "event_type"])
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = e.where("event_type = 'view'").select("event_id", "user_id", "ts", F.col("event_id").alias("v"))
    return surround.asof_join(left, right, ["user_id"], "ts", "event_id", "v", "last_view").select("event_id", F.coalesce("last_view", F.lit(-1)).alias("last_view"))


@named("agg_lineitem", "SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS DECIMAL(18, 2))) AS DECIMAL(28, 2)) AS sum_qty, count(*) AS n, min(l_shipdate) AS first_ship, max(l_shipdate) AS last_ship FROM lineitem GROUP BY 1, 2")
def agg_lineitem(s, d):
    df = load(s, d, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity", "l_shipdate"])
    return surround.aggregate(df, ["l_returnflag", "l_linestatus"], sum_qty=F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("decimal(28,2)"), n=F.count(F.lit(1)), first_ship=F.min("l_shipdate"), last_ship=F.max("l_shipdate"))


@named("cube_prefix", "SELECT coalesce(p_brand, '') AS p_brand, CAST(coalesce(p_size, -1) AS BIGINT) AS p_size, CAST(grouping(p_brand) * 2 + grouping(p_size) AS BIGINT) AS level_id, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_size)")
def cube_prefix(s, d):
    return surround.grouping(load(s, d, "part", ["p_brand", "p_size"]), ["p_brand", "p_size"], "cube", F.count(F.lit(1)).alias("n")).select(F.coalesce("p_brand", F.lit("")).alias("p_brand"), F.coalesce("p_size", F.lit(-1)).cast("long").alias("p_size"), "level_id", "n")


@named("rollup_nation", "SELECT CAST(coalesce(n_regionkey, -1) AS BIGINT) AS n_regionkey, coalesce(n_name, '') AS n_name, CAST(grouping(n_regionkey) * 2 + grouping(n_name) AS BIGINT) AS level_id, count(*) AS n FROM nation JOIN customer ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_name)")
def rollup_nation(s, d):
    n, c = load(s, d, "nation"), load(s, d, "customer", ["c_nationkey"])
    return surround.grouping(n.join(c, n["n_nationkey"] == c["c_nationkey"]), ["n_regionkey", "n_name"], "rollup", F.count(F.lit(1)).alias("n")).select(F.coalesce("n_regionkey", F.lit(-1)).cast("long").alias("n_regionkey"), F.coalesce("n_name", F.lit("")).alias("n_name"), "level_id", "n")


@named("grouping_sets_part", "SELECT coalesce(p_brand, '') AS p_brand, coalesce(p_type, '') AS p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
def grouping_sets_part(s, d):
    df = load(s, d, "part", ["p_brand", "p_type"])
    return df.groupingSets([["p_brand"], ["p_type"], []], "p_brand", "p_type").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("p_brand", F.lit("")).alias("p_brand"), F.coalesce("p_type", F.lit("")).alias("p_type"), "n")


@named("window_rank_supp", "SELECT s_suppkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rank FROM supplier")
def window_rank_supp(s, d):
    df = surround.ranked(load(s, d, "supplier", ["s_suppkey", "s_nationkey", "s_acctbal"]), ["s_nationkey"], [F.desc("s_acctbal"), F.col("s_suppkey")])
    return df.select("s_suppkey", F.col("rank").cast("long").alias("rank"))


@named("window_frame_orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n FROM orders")
def window_frame_orders(s, d):
    return surround.framed(load(s, d, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]), ["o_custkey"], [F.col("o_orderdate"), F.col("o_orderkey")], 2, F.count(F.lit(1)), "n").select("o_orderkey", "n")


@named("topk_parts", "SELECT p_partkey, p_brand FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def topk_parts(s, d):
    return surround.top_k(load(s, d, "part", ["p_partkey", "p_brand", "p_retailprice"]), 3, [F.desc("p_retailprice"), F.col("p_partkey")], ["p_brand"]).select("p_partkey", "p_brand")


@named("setops_orders", "SELECT k FROM ((SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders) UNION (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P' INTERSECT SELECT c_custkey FROM customer WHERE c_nationkey < 5))")
def setops_orders(s, d):
    c, o = load(s, d, "customer"), load(s, d, "orders")
    lone = surround.set_op(c.select(F.col("c_custkey").alias("k")), o.select("o_custkey"), "except")
    both = surround.set_op(o.where("o_orderstatus = 'P'").select("o_custkey"), c.where("c_nationkey < 5").select("c_custkey"), "intersect")
    return surround.set_op(lone, both, "union")


@named("pivot_events", "SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def pivot_events(s, d):
    return surround.pivoted(load(s, d, "events", ["user_id", "event_type"]), ["user_id"], "event_type", ["view", "purchase"], F.count(F.lit(1))).na.fill(0, ["view", "purchase"])


@named("unpivot_parts", "SELECT p_partkey, name, value FROM part UNPIVOT (value FOR name IN (p_brand, p_type))")
def unpivot_parts(s, d):
    return surround.unpivoted(load(s, d, "part", ["p_partkey", "p_brand", "p_type"]), ["p_partkey"], ["p_brand", "p_type"])


# --- functions ----------------------------------------------------------------------------------------------------------------
@named("string_docs", "SELECT doc_id, lower(regexp_extract(text, '([^\\s]+)', 1)) AS head, CAST(length(text) AS BIGINT) AS n FROM documents")
def string_docs(s, d):
    return load(s, d, "documents", ["doc_id", "text"]).select("doc_id", C.first_word(F.col("text")).alias("head"), F.char_length("text").cast("long").alias("n"))


@named("date_orders", "SELECT date_trunc('month', o_orderdate)::DATE AS m, count(*) AS n, max(CAST(datediff('day', DATE '1992-01-01', o_orderdate::DATE) AS BIGINT)) AS last_day FROM orders GROUP BY 1")
def date_orders(s, d):
    return load(s, d, "orders", ["o_orderdate"]).groupBy(C.month_start(F.col("o_orderdate")).cast("date").alias("m")).agg(F.count(F.lit(1)).alias("n"), F.max(C.days_between(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long")).alias("last_day"))


@named("math_parts", "SELECT p_partkey, CAST(floor(log2(p_size + 1)) AS BIGINT) AS bits, greatest(p_size, 10) AS g FROM part")
def math_parts(s, d):
    return load(s, d, "part", ["p_partkey", "p_size"]).select("p_partkey", F.floor(C.log2(F.col("p_size") + 1)).cast("long").alias("bits"), F.greatest("p_size", F.lit(10)).alias("g"))


@named("hash_cells", "SELECT count(*) AS n, count(DISTINCT a) AS n_keys FROM cs", "cs")
def hash_cells(s, d):
    """Rows and keys summed over the cells of one variable: as a key has one cell, no key counts twice."""
    per = relation(s, d, "cs").groupBy(C.cell_of(F.col("o_custkey"), 8).alias("cell")).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("o_custkey").alias("k"))
    return per.agg(F.sum("n").alias("n"), F.sum("k").alias("n_keys"))


@named("array_meet", "SELECT c_custkey, list_sort(list_intersect(f, o)) AS both_days FROM (SELECT o_custkey AS c_custkey, list(DISTINCT month(o_orderdate)) FILTER (o_orderstatus = 'F') AS f, list(DISTINCT month(o_orderdate)) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1) WHERE len(list_intersect(f, o)) > 0")
def array_meet(s, d):
    o = load(s, d, "orders", ["o_custkey", "o_orderdate", "o_orderstatus"])
    m = lambda st: F.sort_array(F.collect_set(F.when(F.col("o_orderstatus") == st, F.month("o_orderdate").cast("long"))))
    g = o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(m("F").alias("f"), m("O").alias("o"))
    return g.select("c_custkey", C.meet_lists(F.col("f"), F.col("o")).alias("both_days")).where("size(both_days) > 0")


@named("udf_meet", "SELECT c_custkey, CAST(len(list_intersect(f, o)) AS BIGINT) AS n FROM (SELECT o_custkey AS c_custkey, list(DISTINCT month(o_orderdate)) FILTER (o_orderstatus = 'F') AS f, list(DISTINCT month(o_orderdate)) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1) WHERE f IS NOT NULL AND o IS NOT NULL")
def udf_meet(s, d):
    from .functions.udf import meet_udf

    o = load(s, d, "orders", ["o_custkey", "o_orderdate", "o_orderstatus"])
    m = lambda st: F.sort_array(F.collect_set(F.when(F.col("o_orderstatus") == st, F.month("o_orderdate").cast("long"))))
    g = o.groupBy(F.col("o_custkey").alias("c_custkey")).agg(m("F").alias("f"), m("O").alias("o")).where("size(f) > 0 and size(o) > 0")
    return g.select("c_custkey", F.size(meet_udf("f", "o")).cast("long").alias("n"))


@named("map_ops", "SELECT user_id, CAST(count(DISTINCT event_type) AS BIGINT) AS kinds, count(*) FILTER (event_type = 'view') AS views FROM events GROUP BY user_id")
def map_ops(s, d):
    g = load(s, d, "events", ["user_id", "event_type"]).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = g.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.try_element_at("m", F.lit("view")), F.lit(0)).alias("views"))


@named("json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def json_props(s, d):
    return load(s, d, "events", ["event_id", "props"]).select("event_id", C.json_long(F.col("props"), "$.k").alias("k"))


@named("cond_null", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'mid' ELSE 'large' END AS bracket FROM part")
def cond_null(s, d):
    return load(s, d, "part", ["p_partkey", "p_size"]).select("p_partkey", C.bracket(F.col("p_size"), [10, 30], ["small", "mid", "large"]).alias("bracket"))


@named("bit_masks", "SELECT user_id, CAST(bit_or(CASE event_type WHEN 'view' THEN 1 WHEN 'click' THEN 2 WHEN 'purchase' THEN 4 WHEN 'signup' THEN 8 ELSE 16 END) AS BIGINT) AS mask FROM events GROUP BY user_id")
def bit_masks(s, d):
    tag = F.when(F.col("event_type") == "view", 0).when(F.col("event_type") == "click", 1).when(F.col("event_type") == "purchase", 2).when(F.col("event_type") == "signup", 3).otherwise(4)
    return load(s, d, "events", ["user_id", "event_type"]).groupBy("user_id").agg(F.bit_or(C.tag_mask(tag)).alias("mask"))


@named("udtf_rule", TRI, "cs sn cn")
def udtf_rule(s, d):
    """The triangle as a table function over cells of the first variable's hash, called from SQL."""
    from .functions.udf import register

    register(s)
    r = W.w01_relations(s, d)
    edge = lambda df, atom: W.longs(df.toDF("x", "y")).select(F.lit(atom).alias("atom"), "x", "y")
    rows = edge(r["R"], 0).unionByName(edge(r["T"], 2)).withColumn("cell", C.cell_of(F.col("x"), 8))
    rows = rows.unionByName(edge(r["S"], 1).withColumn("cell", F.explode(F.array(*(F.lit(i) for i in range(8))))))
    rows.createOrReplaceTempView("walk_rows")
    return s.sql("SELECT a, b, c FROM walk_triangle(TABLE(walk_rows) PARTITION BY cell)")


@named("udtf_any_rule", TRI, "cs sn cn")
def udtf_any_rule(s, d):
    """The same through the table function that takes any rule as its first argument."""
    from .functions.udf import register, rule_rows

    register(s)
    rels = {n: W.longs(df) for n, df in W.w01_relations(s, d).items()}
    rule_rows(W.TRIANGLE, rels, 8).createOrReplaceTempView("rule_rows")
    return s.sql(f"SELECT a, b, c FROM walk_rule('{W.TRIANGLE}', TABLE(rule_rows) PARTITION BY cell)")


@named("rule_source_nation", HOP3.format(e="nn"), "nn")
def rule_source_nation(s, d):
    """A rule read as a table: the data source walks the relations' files, a part of the first variable's values in each task."""
    from .sources.rule_source import RuleSource

    path = fresh_path(s, "rule-source")
    W.longs(relation(s, d, "nn").toDF("u", "v")).write.parquet(path)
    s.dataSource.register(RuleSource)
    return s.read.format("rule").option("rule", "Q(a,b,c) :- E(a,b), E(b,c), E(a,c)").option("parts", "4").option("relation_E", path).load()


# --- windows of events --------------------------------------------------------------------------------------------------------
@named("tumbling_events", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS begins, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS ends, count(*) AS n FROM events GROUP BY 1")
def tumbling_events(s, d):
    return streams.windowed_counts(load(s, d, "events", ["ts"]), "tumbling")


@named("sliding_events", "SELECT b AS begins, b + INTERVAL 2 DAY AS ends, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS b FROM events) GROUP BY b")
def sliding_events(s, d):
    return streams.windowed_counts(load(s, d, "events", ["ts"]), "sliding", size="2 days", slide="1 day")


@named(
    "session_windows",
    "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) "
    "SELECT user_id, min(ts) AS begins, max(ts) + INTERVAL 6 HOUR AS ends, count(*) AS n FROM g GROUP BY user_id, k",
)
def session_windows(s, d):
    return streams.windowed_counts(load(s, d, "events", ["user_id", "ts"]), "session", keys=("user_id",), size="6 hours")


@named(
    "windowed_triangles",
    "WITH e AS (SELECT DISTINCT time_bucket(INTERVAL 1 DAY, ts) AS w, u, v FROM (SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v, ts FROM events) WHERE v IS NOT NULL AND u <> v) "
    "SELECT x.w, x.u AS a, x.v AS b, y.v AS c FROM e x JOIN e y ON x.w = y.w AND x.v = y.u JOIN e z ON z.w = x.w AND z.u = x.u AND z.v = y.v",
)
def windowed_triangles(s, d):
    from .sources.tables import next_in_order

    e = next_in_order(load(s, d, "events", ["event_id", "ts", "user_id"]), ["ts", "event_id"], "user_id")
    edges = e.where("next is not null and user_id != next").select(F.col("user_id").alias("u"), F.col("next").alias("v"), "ts")
    return streams.windowed_triangles(edges)


UTD3 = "SELECT x.u AS a, x.t AS b, y.d AS c FROM (SELECT DISTINCT user_id AS u, event_type AS t FROM events) x JOIN (SELECT DISTINCT event_type AS t, CAST(day(ts) AS BIGINT) AS d FROM events) y ON x.t = y.t JOIN (SELECT DISTINCT user_id AS u, CAST(day(ts) AS BIGINT) AS d FROM events) z ON z.u = x.u AND z.d = y.d"


@named("delta_events", UTD3)
def delta_events(s, d):
    """User, type, day triangles, first of days 1 to 20, then the answers that days 21 and on add: together the whole."""
    e = load(s, d, "events", ["user_id", "event_type", "ts"]).select("user_id", "event_type", F.dayofmonth("ts").cast("long").alias("d"))
    pairs = {"R": ("user_id", "event_type"), "S": ("event_type", "d"), "T": ("user_id", "d")}
    q = "Q(a,b,c) :- R(a,b), S(b,c), T(a,c)"
    old = {n: e.where("d <= 20").select(*c).distinct() for n, c in pairs.items()}
    new = {n: e.where("d > 20").select(*c).distinct().join(old[n], [*c], "left_anti") for n, c in pairs.items()}
    return run(q, old, "levels").unionByName(streams.delta_answers(q, old, new))


@named("stream_hop_delta", HOP3.format(e="hop"), "hop")
def stream_hop_delta(s, d):
    """Triangles of hops that arrive in three batches: each batch adds the answers that its own edges close."""
    return W.longs(streams.streamed_answers("Q(a,b,c) :- E(a,b), E(b,c), E(a,c)", "E", relation(s, d, "hop"), 3), ["a", "b", "c"])


__all__ = ["ORACLES", "QUERIES", "KeyFrame", "Prepared"]
