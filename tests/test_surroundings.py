import datetime as dt
import shutil
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from triewalk.functions import udf
from triewalk.operators import families, surround
from triewalk.sources.tables import load, load_text, next_in_order, save
from triewalk.streaming import streams

from .conftest import SMALL


def got(df):
    return sorted(tuple(r) for r in df.collect())


def test_sources_and_sinks(spark, tmp_path):
    n = load(spark, SMALL, "nation", ["n_nationkey", "n_name"], F.col("n_nationkey") < 5)
    plan = n._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(n_nationkey), LessThan(n_nationkey,5)]" in plan and "n_regionkey" not in plan
    for fmt in ("csv", "json", "orc", "parquet"):
        save(n, str(tmp_path / fmt), fmt)
        assert got(load_text(spark, str(tmp_path / fmt), "n_nationkey int, n_name string", fmt)) == got(n)


def test_udfs(spark):
    udf.register(spark)
    df = spark.sql("select meet_arrays(array(1L, 3L, 5L), array(3L, 4L, 5L)) as m")
    assert df.first()["m"] == [3, 5]
    e = spark.createDataFrame([("g", 1, 2), ("g", 2, 3), ("g", 1, 3), ("h", 1, 2)], "k string, u long, v long")
    assert got(udf.small_triangles(e, "k")) == [("g", 1, 2, 3)]
    a = spark.createDataFrame([(1, 2), (2, 3)], "k long, x long")
    b = spark.createDataFrame([(1, 9), (1, 8)], "k long, y long")
    assert got(udf.joined_groups(a, b, "k")) == [(1, 2, 8), (1, 2, 9)]
    t = spark.createDataFrame([(0, 1), (0, 2), (1, 2)], "t int, x long")
    assert t.agg(udf.meet_size_udaf("x", "t")).first()[0] == 1
    assert t.agg(udf.sorted_list("x").alias("l")).first()["l"] == [1, 2]


def test_sampled_is_stable(spark):
    df = spark.range(1000)
    assert got(surround.sampled(df, 0.2, "id")) == got(surround.sampled(df.repartition(7), 0.2, "id"))


EVENTS = "event_id long, ts timestamp, user_id long, event_type string"


@pytest.fixture
def days(spark, tmp_path):
    """Events of three days, a file a day."""
    e = load(spark, SMALL, "events", ["event_id", "ts", "user_id", "event_type"])
    for i in (1, 2, 3):
        e.where(F.dayofmonth("ts") == i).coalesce(1).write.parquet(str(tmp_path / "in" / f"{i}"))
    return str(tmp_path / "in" / "*")


def run_stream(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return q


def test_streamed_windows_and_dedup(spark, days):
    src = streams.stream_files(spark, days, EVENTS)
    run_stream(streams.windowed_counts(src, "tumbling", late="1 day"), "w_tumbling", "complete")
    want = streams.windowed_counts(spark.read.parquet(days), "tumbling")
    assert got(spark.table("w_tumbling")) == got(want)
    run_stream(streams.dedup(src.select("user_id", "ts"), ["user_id"], "ts", "5 days"), "w_dedup", "append")
    assert spark.table("w_dedup").count() == spark.read.parquet(days).select("user_id").distinct().count()


def test_adjacency_state(spark, days):
    src = streams.stream_files(spark, days, EVENTS).select("user_id", F.dayofmonth("ts").cast("long").alias("d"))
    run_stream(streams.adjacency(src, "user_id", "d"), "w_adj", "update")
    last = spark.table("w_adj").groupBy("user_id").agg(F.max("degree").alias("n"))
    want = spark.read.parquet(days).groupBy("user_id").agg(F.count_distinct(F.dayofmonth("ts")).alias("n"))
    assert got(last) == got(want)


def test_interval_join(spark):
    t0 = dt.datetime(2024, 1, 1)
    a = spark.createDataFrame([(1, t0)], "k long, ts timestamp")
    b = spark.createDataFrame([(1, t0 + dt.timedelta(hours=h)) for h in (0, 1, 3)], "k long, ts timestamp")
    assert streams.interval_join(a, b, "k", "ts", "2 hours").count() == 2


def test_delta_stream(spark, days, tmp_path):
    sink = streams.DeltaQuery("Q(a,b,c) :- E(a,b), E(b,c)", "E", lambda b: b.selectExpr("user_id as u", "event_id % 15 as v"), str(tmp_path / "state"))
    src = streams.stream_files(spark, days, EVENTS)
    src.writeStream.foreachBatch(sink).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination(300)
    from triewalk.operators.engine import run

    whole = spark.read.parquet(days).selectExpr("user_id as u", "event_id % 15 as v")
    assert len(sink.batches(spark)) == 3
    assert got(sink.answers(spark)) == got(run("Q(a,b,c) :- E(a,b), E(b,c)", {"E": whole}))


def test_delta_stream_goes_on_after_a_restart(spark, days, tmp_path):
    from triewalk.operators.engine import run

    make = lambda b: b.selectExpr("user_id as u", "event_id % 15 as v")
    q, state = "Q(a,b,c) :- E(a,b), E(b,c)", str(tmp_path / "state")

    def go():
        """Whatever files there are; a sink of its own each time, as after a lost driver."""
        sink = streams.DeltaQuery(q, "E", make, state)
        src = streams.stream_files(spark, str(tmp_path / "arriving"), EVENTS)
        src.writeStream.foreachBatch(sink).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination(300)
        return streams.DeltaQuery(q, "E", make, state).answers(spark)

    files = sorted(Path(days).parent.rglob("*.parquet"))
    (tmp_path / "arriving").mkdir()
    for f in files[:1]:
        shutil.copy(f, tmp_path / "arriving" / f"0-{f.name}")
    go()
    for i, f in enumerate(files[1:], 1):
        shutil.copy(f, tmp_path / "arriving" / f"{i}-{f.name}")
    assert got(go()) == got(run(q, {"E": make(spark.read.parquet(days))}))


def test_next_in_order_of_one_crowded_moment(spark):
    """All rows at one moment: ranges go by the id then."""
    df = spark.range(1000).selectExpr("timestamp'2024-01-01' as ts", "id", "id * 7 % 13 as u")
    rows = {r["id"]: r["next"] for r in next_in_order(df, ["ts", "id"], "u").collect()}
    assert rows == {i: (i + 1) * 7 % 13 if i < 999 else None for i in range(1000)}


def test_degree_profile_of_one_degree(spark):
    profile = got(families.degree_profile(spark.range(500).selectExpr("id as u", "id + 1 as v"), "u"))
    assert profile == [(i, 1) for i in range(500)]


def test_rule_source_and_function(spark, tmp_path):
    from triewalk.functions.udf import register, rule_rows
    from triewalk.operators.engine import run
    from triewalk.plans.ir import QueryError
    from triewalk.functions.udf import walk_rule_arrays
    from triewalk.plans.parse import rule
    from triewalk.sources.rule_source import RuleSource

    e = spark.range(60).selectExpr("id % 8 as u", "id * 5 % 9 as v").distinct()
    e.write.parquet(str(tmp_path / "e"))
    spark.dataSource.register(RuleSource)
    q = "Q(a,b,c,d) :- E(a,b), E(b,c), E(c,d), E(a,d)"
    want = got(run(q, {"E": e}))
    assert want and got(spark.read.format("rule").option("rule", q).option("parts", 3).option("relation_E", str(tmp_path / "e")).load()) == want
    register(spark)
    rule_rows(q, {"E": e}, 3).createOrReplaceTempView("some_rows")
    assert got(spark.sql(f"SELECT * FROM walk_rule('{q}', TABLE(some_rows) PARTITION BY cell)")) == want
    with pytest.raises(QueryError):
        list(walk_rule_arrays(rule("Q(a) :- E(a,a)"), []))


def test_streamed_answers_of_no_rows(spark):
    none = spark.createDataFrame([], "u long, v long")
    assert got(streams.streamed_answers("Q(a,b,c) :- E(a,b), E(b,c)", "E", none, 2)) == []


def test_density_counters_beyond_the_driver(spark, monkeypatch):
    """Probes are counted over the executors, and are those of the scalar hash walk, which the driver's rows limit."""
    from triewalk import catalog
    from triewalk import workloads as W
    from triewalk.kernel.cursor import OpCounter
    from triewalk.kernel.hashwalk import hash_walk
    from triewalk.operators import costs

    from .conftest import SMALL

    ops = OpCounter()
    n = sum(1 for _ in hash_walk(costs.local_atoms(W.w01_prepared(spark, SMALL), ["a", "b", "c"]), 3, ops))
    monkeypatch.setattr(costs, "LOCAL_ROWS", 10)
    assert ("same nation", n, ops.total("probe")) in [tuple(r) for r in catalog.density_counters(spark, SMALL).collect()]


@pytest.mark.parametrize("name", ["counterexample_256", "counterexample_sweep_256", "counterexample_sweep_65536", "density_ops", "growth_tri", "tri_hub_pairwise", "unary_trace"])
def test_instances_are_made_of_a_given_table(spark, tmp_path, name):
    """Where lineitem is missing, a query over an instance that is made of it fails."""
    from pyspark.errors import AnalysisException

    from triewalk.catalog import QUERIES

    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path))
