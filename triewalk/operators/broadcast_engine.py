"""The join without moving the largest atom: all others are sent whole to every executor, once their size is known to be small."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..kernel.walk import ColumnTrie, count_answers, walk_batches
from ..plans.choice import BROADCAST_ROWS
from ..plans.rewrite import KeyFrame
from .cell_engine import participants


#: Rows a task below which the largest atom is dealt out anew: a small table may lie in one file, and the walk is what takes time.
DEALT_ROWS = 1_000_000


class TooLarge(ValueError):
    """The atoms to be broadcast hold more rows than allowed."""


def run_broadcast(spark: SparkSession, frames: list[KeyFrame], order: list[str], sizes: list[int] | None = None, most: int = BROADCAST_ROWS, batch_rows: int = 1 << 16, measure: str | None = None) -> DataFrame:
    """All bindings as longs, or measure="count": their number a batch (n). Each batch of the largest atom is walked with the broadcast
    ones; its rows are distinct, so answers are too."""
    sizes = sizes or [f.df.count() if f.rows is None else f.rows for f in frames]
    big = max(range(len(frames)), key=lambda i: sizes[i])
    if sum(sizes) - sizes[big] > most:
        raise TooLarge(f"{sum(sizes) - sizes[big]} rows to broadcast; {most} are allowed")
    # atoms of one source are sent once; a trie of theirs is built once a task
    small, place = {}, {}
    for i, f in enumerate(frames):
        if i != big:
            place[i] = (f.source, f.columns) if f.source else i
            if place[i] not in small:
                small[place[i]] = [np.asarray(c) for c in f.df.select(*f.vars).toArrow().columns]
    shared = spark.sparkContext.broadcast(small)
    levels, arity = participants([f.vars for f in frames], order), len(frames[big].vars)
    n = len(frames)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        built = {k: ColumnTrie.of([c.astype(np.int64) for c in cols]) for k, cols in shared.value.items()}
        tries: dict[int, ColumnTrie] = {i: built[k] for i, k in place.items()}
        for b in batches:
            if not b.num_rows:
                continue
            tries[big] = ColumnTrie.of([b.column(d).to_numpy(zero_copy_only=False).astype(np.int64) for d in range(arity)])
            if measure == "count":
                yield pa.record_batch([pa.array([count_answers([tries[i] for i in range(n)], levels, batch_rows)], pa.int64())], names=["n"])
                continue
            for columns in walk_batches([tries[i] for i in range(n)], levels, batch_rows):
                yield pa.record_batch([pa.array(c) for c in columns], names=order)

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = frames[big].df.select(*frames[big].vars)
    if sizes[big] <= parts * DEALT_ROWS:
        rows = rows.repartition(parts, *rows.columns)
    return rows.mapInArrow(run, "n long" if measure == "count" else ", ".join(f"`{v}` long" for v in order))
