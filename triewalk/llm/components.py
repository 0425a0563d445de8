"""Connected components of links by joins: every id falls to its least neighbour, pointers are followed to their ends, and the
links are drawn anew between the ends, until none is left. Links shrink from round to round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize


def _ends(parents: DataFrame) -> DataFrame:
    """(id, root) with root followed to its end; parents hold a row for every id, and a root is never above its id."""
    while True:
        further = parents.select(F.col("id").alias("root"), F.col("root").alias("far"))
        jumped = materialize(parents.join(further, "root").select("id", F.col("root").alias("was"), F.col("far").alias("root")), "component-parents")
        parents = jumped.select("id", "root")
        if not jumped.where("was != root").limit(1).count():
            return parents


def components(links: DataFrame) -> DataFrame:
    """(id, root) of every id in links (a, b): root is the least id reachable. No row for ids without other ids linked to them."""
    edges = links.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    edges = materialize(edges, "component-links")
    labels = None
    while True:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        parents = _ends(materialize(both.groupBy(F.col("a").alias("id")).agg(F.least(F.first("a"), F.min("b")).alias("root")), "component-parents"))
        if labels is None:
            labels = parents
        else:
            moved = parents.select(F.col("id").alias("root"), F.col("root").alias("to"))
            labels = materialize(labels.join(moved, "root", "left").select("id", F.coalesce("to", "root").alias("root")), "component-labels")
        pa, pb = parents.select(F.col("id").alias("a"), F.col("root").alias("ra")), parents.select(F.col("id").alias("b"), F.col("root").alias("rb"))
        drawn = edges.join(pa, "a").join(pb, "b").where("ra != rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct()
        edges = materialize(drawn, "component-links")
        if not edges.limit(1).count():
            return labels
