"""Streams around the joins: delta evaluation of a rule, windows, interval joins, dedup, adjacency state, windowed triangles."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.engine import Prepared, execute
from ..plans.ir import JoinQuery
from ..plans.parse import rule
from ..plans.rewrite import KeyFrame, key_frame, variable_types
from ..sources.scratch import fresh_path


def stream_files(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def delta_answers(q: JoinQuery | str, old: dict[str, DataFrame], new: dict[str, DataFrame]) -> DataFrame:
    """Answers that appear when new rows join old ones: for each atom its new rows, atoms before it with all rows, those after with
    old rows only, so no answer arises twice. new must hold no row of old (set semantics)."""
    q = rule(q) if isinstance(q, str) else q
    types, order = variable_types(q, old), list(q.vars)
    both = {n: old[n].unionByName(new[n]) if n in new else old[n] for n in old}
    out = None
    for i, atom in enumerate(q.body):
        if atom.relation not in new:
            continue
        frames: list[KeyFrame] = []
        for j, other in enumerate(q.body):
            source = new if j == i else both if j < i else old
            frames.append(key_frame(other, source[other.relation], order, types))
        first = list(frames[i].vars)
        found = execute(Prepared(q.head, frames, [], types, old), "levels", [*first, *(v for v in order if v not in first)])
        out = found if out is None else out.unionByName(found)
    return out


class DeltaQuery:
    """A foreachBatch sink that keeps relations and the rule's answers as Parquet under a folder, batch by batch.

    A batch's folder is named by its id and rewritten whole if the batch is repeated, so the result is the same after recovery.
    """

    def __init__(self, q: str, name: str, make: Callable[[DataFrame], DataFrame], folder: str):
        self.q, self.name, self.make, self.folder = q, name, make, folder

    def _read(self, spark: SparkSession, kind: str, upto: int, schema) -> DataFrame:
        parts = [f"{self.folder}/{kind}/{i}" for i in range(upto)]
        return spark.read.schema(schema).parquet(*parts) if parts else spark.createDataFrame([], schema)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        rows = self.make(batch).distinct()
        old = self._read(spark, "rows", batch_id, rows.schema)
        fresh = rows.join(old, rows.columns, "left_anti")
        fresh.write.mode("overwrite").parquet(f"{self.folder}/rows/{batch_id}")
        fresh = spark.read.schema(rows.schema).parquet(f"{self.folder}/rows/{batch_id}")
        found = delta_answers(self.q, {self.name: old}, {self.name: fresh})
        found.write.mode("overwrite").parquet(f"{self.folder}/answers/{batch_id}")

    def batches(self, spark: SparkSession) -> list[str]:
        """Folders of the batches whose answers are complete, as the store lists them: nothing is kept in the driver, so a sink made anew goes on."""
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
        found = hadoop.Path(f"{self.folder}/answers").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).globStatus(hadoop.Path(f"{self.folder}/answers/*/_SUCCESS"))
        return sorted(f.getPath().getParent().toString() for f in found or ())

    def answers(self, spark: SparkSession) -> DataFrame:
        """All answers so far; an empty frame of no columns before the first batch."""
        parts = self.batches(spark)
        return spark.read.parquet(*parts) if parts else spark.createDataFrame([], "struct<>")


def streamed_answers(q: str, name: str, rows: DataFrame, batches: int) -> DataFrame:
    """Answers of a rule over one relation whose rows arrive as a stream of about that many batches, by delta queries.

    Rows are laid down in the shared folder and read as a file stream; state, answers and the stream's checkpoint stay there too,
    so a lost executor or a restarted batch changes nothing.
    """
    spark = rows.sparkSession
    folder = fresh_path(spark, "stream")
    files = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) // batches)
    rows.repartition(files * batches).write.parquet(f"{folder}/in")
    sink = DeltaQuery(q, name, lambda batch: batch, f"{folder}/state")
    writer = stream_files(spark, f"{folder}/in", rows.schema, files).writeStream.foreachBatch(sink)
    writer.option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start().awaitTermination()
    if sink.batches(spark):
        return sink.answers(spark)
    types = variable_types(rule(q), {name: rows})
    return spark.createDataFrame([], T.StructType([T.StructField(v, types[v]) for v in rule(q).head]))


def windowed_counts(df: DataFrame, kind: str, ts: str = "ts", keys: tuple[str, ...] = (), size: str = "1 day", slide: str | None = None, late: str | None = None) -> DataFrame:
    """Counts by tumbling, sliding or session windows; with a watermark if `late` is given. For batches and streams."""
    df = df.withWatermark(ts, late) if late else df
    w = F.session_window(ts, size) if kind == "session" else F.window(ts, size, slide) if kind == "sliding" else F.window(ts, size)
    return df.groupBy(*keys, w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(*keys, F.col("w.start").alias("begins"), F.col("w.end").alias("ends"), "n")


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, within: str, late: str = "1 day") -> DataFrame:
    """left and right rows of one key with right's time at or after left's, within the interval; state is bounded by watermarks."""
    a = left.withWatermark(ts, late).alias("l")
    b = right.withWatermark(ts, late).alias("r")
    cond = (F.col(f"l.{key}") == F.col(f"r.{key}")) & (F.col(f"r.{ts}") >= F.col(f"l.{ts}")) & (F.col(f"r.{ts}") <= F.col(f"l.{ts}") + F.expr(f"INTERVAL {within}"))
    return a.join(b, cond)


def dedup(df: DataFrame, keys: list[str], ts: str, late: str) -> DataFrame:
    return df.withWatermark(ts, late).dropDuplicatesWithinWatermark(keys)


def adjacency(df: DataFrame, u: str, v: str) -> DataFrame:
    """For each new edge (u, v) of a stream: u and the number of its neighbours so far, from a sorted list kept per u."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        known = set(state.get[0]) if state.exists else set()
        for g in batches:
            known.update(int(x) for x in g[v])
        state.update((sorted(known),))
        yield pd.DataFrame({u: [key[0]], "degree": [len(known)]})

    return df.groupBy(u).applyInPandasWithState(run, f"{u} long, degree long", "known array<long>", "update", "NoTimeout")


def windowed_triangles(edges: DataFrame, size: str = "1 day") -> DataFrame:
    """Triangles whose three edges fall in one window: the window is one more variable of the rule. edges: u, v, ts."""
    e = edges.select(F.window("ts", size)["start"].alias("w"), "u", "v").distinct()
    from ..operators.engine import run

    return run("Q(w,a,b,c) :- E(w,a,b), E(w,b,c), E(w,a,c)", {"E": e})
