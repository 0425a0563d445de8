"""The distributed meet of unary relations: range-aligned with the skipping kernel, by tag masks, or by semi joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernel.meet import meet_arrays


def key_intervals(df: DataFrame, key: str, parts: int = 64) -> list[tuple]:
    """(least, greatest) key of `parts` slices of the key range; at most `parts` pairs come to the driver."""
    lo, hi = df.agg(F.min(key), F.max(key)).first()
    if lo is None:
        return []
    width = max(1, -(-(hi - lo + 1) // parts))
    rows = df.groupBy(F.expr(f"(`{key}` - {lo}L) div {width}L").alias("slot")).agg(F.min(key).alias("a"), F.max(key).alias("z")).collect()
    return sorted((r["a"], r["z"]) for r in rows)


def intersect_intervals(lists: list[list[tuple]]) -> list[tuple]:
    out = lists[0]
    for other in lists[1:]:
        out = [(max(a, c), min(z, d)) for a, z in out for c, d in other if max(a, c) <= min(z, d)]
    return sorted(out)


def prune(dfs: list[DataFrame], key: str) -> list[DataFrame]:
    """Whole-number keys: only the ranges that all inputs may share are read, as a filter that reaches the scan."""
    ranges = intersect_intervals([key_intervals(d, key) for d in dfs])
    if not ranges:
        return [d.limit(0) for d in dfs]
    merged: list[list] = []
    for a, z in ranges:
        if merged and a <= merged[-1][1] + 1:
            merged[-1][1] = max(z, merged[-1][1])
        else:
            merged.append([a, z])
    keep = F.lit(False)
    for a, z in merged:
        keep = keep | F.col(key).between(a, z)
    return [d.where(keep) for d in dfs]


def skip_meet(dfs: list[DataFrame], key: str, how: str = "range", pruned: bool = False) -> DataFrame:
    """Distinct keys common to all inputs; nulls never match. range needs whole-number keys and gives sorted output."""
    dfs = [d.select(F.col(key)).where(F.col(key).isNotNull()) for d in dfs]
    if pruned:
        dfs = prune(dfs, key)
    dfs = [d.distinct() for d in dfs]
    if len(dfs) == 1:
        return dfs[0]
    if how == "semi":
        out = dfs[0]
        for d in dfs[1:]:
            out = out.join(d, key, "left_semi")
        return out
    tagged = None
    for i, d in enumerate(dfs):
        part = d.select(key, F.lit(i).alias("tag"))
        tagged = part if tagged is None else tagged.unionByName(part)
    if how == "count":
        mask = F.bit_or(F.pow(F.lit(2), F.col("tag")).cast("long"))
        return tagged.groupBy(key).agg(mask.alias("mask")).where(F.bit_count("mask") == len(dfs)).select(key)
    if how != "range":
        raise ValueError(how)
    k, kind = len(dfs), dfs[0].schema[key].dataType
    n = int(dfs[0].sparkSession.conf.get("spark.sql.shuffle.partitions"))
    aligned = tagged.withColumn(key, F.col(key).cast("long")).repartitionByRange(n, key).sortWithinPartitions("tag", key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = [[] for _ in range(k)]
        for b in batches:
            keys, tags = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            for t in np.unique(tags).tolist():
                held[t].append(keys[tags == t])
        if all(held):
            yield pa.record_batch([pa.array(meet_arrays([np.concatenate(h) for h in held]))], names=[key])

    return aligned.mapInArrow(run, f"`{key}` long").select(F.col(key).cast(kind).alias(key))
