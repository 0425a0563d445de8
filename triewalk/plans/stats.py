"""Sizes and projection counts of key frames: one small aggregate a frame, exact for certificates, sketched for planning."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from .rewrite import KeyFrame


@dataclass
class FrameStats:
    rows: int
    distinct: dict[frozenset[str], int]


def frame_stats(frame: KeyFrame, exact: bool = True, sets: list[frozenset[str]] | None = None) -> FrameStats:
    """Rows and distinct counts of variable sets (by default each single variable)."""
    sets = sets if sets is not None else [frozenset([v]) for v in frame.vars]
    if exact:
        aggs = [F.count_distinct(*sorted(s)) for s in sets]
    else:
        aggs = [F.approx_count_distinct(F.struct(*sorted(s)) if len(s) > 1 else F.col(next(iter(s))), 0.02) for s in sets]
    row = frame.df.agg(F.count(F.lit(1)).alias("n"), *(a.alias(f"d{i}") for i, a in enumerate(aggs))).first()
    return FrameStats(row["n"], {s: row[f"d{i}"] for i, s in enumerate(sets)})
