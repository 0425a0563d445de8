"""Sorted layouts of relations by column order: made when first asked for, kept, and brought up to date by deltas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


class LayoutCatalog:
    """Bucketed and sorted tables named by relation and column order; joins on the bucket columns need no shuffle."""

    def __init__(self, spark: SparkSession, prefix: str = "layout", buckets: int = 8):
        self.spark, self.prefix, self.buckets = spark, prefix, buckets
        self.known: dict[tuple[str, tuple[str, ...]], str] = {}

    def _name(self, rel: str, cols: tuple[str, ...]) -> str:
        return "_".join([self.prefix, rel, *cols])

    def build(self, rel: str, df: DataFrame, cols: list[str]) -> DataFrame:
        """The table for one order of columns; a second call returns what is there."""
        key = (rel, tuple(cols))
        if key not in self.known:
            name = self._name(*key)
            self._write(df.select(*cols).distinct(), name, cols)
            self.known[key] = name
        return self.spark.table(self.known[key])

    def _write(self, df: DataFrame, name: str, cols: list[str], mode: str = "overwrite") -> None:
        df.repartition(self.buckets, cols[0]).write.mode(mode).format("parquet").bucketBy(self.buckets, cols[0]).sortBy(*cols).saveAsTable(name)

    def refresh(self, rel: str, delta: DataFrame) -> None:
        """Appends the rows of a delta that a layout lacks, to every layout of the relation."""
        for (r, cols), name in self.known.items():
            if r == rel:
                fresh = delta.select(*cols).distinct().join(self.spark.table(name), [*cols], "left_anti")
                self._write(fresh, name, list(cols), "append")

    def compact(self, rel: str) -> None:
        """Rewrites the layouts of a relation so each bucket is one sorted file again."""
        for (r, cols), name in list(self.known.items()):
            if r == rel:
                new = f"{name}_c"
                self._write(self.spark.table(name).distinct(), new, list(cols))
                self.spark.sql(f"DROP TABLE {name}")
                self.spark.sql(f"ALTER TABLE {new} RENAME TO {name}")

    def drop(self) -> None:
        for name in self.known.values():
            self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        self.known.clear()
