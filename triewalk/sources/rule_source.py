"""A rule over Parquet relations as a table: spark.read.format("rule").

Options: rule; relation_<name> = path of each relation; parts = tasks, each of which walks the values of the first variable that
hash to it. A task reads the relations itself, so together they may take RULE_BYTES at most; larger ones go through the engines.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.udf import walk_rule_arrays
from ..plans.parse import rule

RULE_BYTES = 256 << 20


def _dataset(uri: str):
    import pyarrow.dataset as ds
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri("file://" + uri.removeprefix("file:").replace("///", "/") if uri.startswith(("file:", "/")) else uri)
    size = sum(f.size for f in store.get_file_info(fs.FileSelector(path, recursive=True)) if f.size)
    return ds.dataset(path, filesystem=store, format="parquet", exclude_invalid_files=True), size


class RuleSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rule"

    def schema(self) -> T.StructType:
        return T.StructType([T.StructField(v, T.LongType()) for v in rule(self.options["rule"]).vars])

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return RuleReader(dict(self.options))


class RuleReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.rule, self.parts = options["rule"], int(options.get("parts", "1"))
        # option names come in lower case
        self.paths = {a.relation: options.get(f"relation_{a.relation}") or options[f"relation_{a.relation.lower()}"] for a in rule(self.rule).body}

    def partitions(self) -> list[InputPartition]:
        total = sum(_dataset(p)[1] for p in set(self.paths.values()))
        if total > RULE_BYTES:
            raise ValueError(f"{total} bytes of relations; {RULE_BYTES} are allowed")
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        q = rule(self.rule)
        columns = []
        for a in q.body:
            table = _dataset(self.paths[a.relation])[0].to_table().drop_null()
            columns.append([c.to_numpy().astype(np.int64) for c in table.columns])
            if q.vars[0] in a.terms:
                mine = columns[-1][a.terms.index(q.vars[0])] % self.parts == partition.value
                columns[-1] = [c[mine] for c in columns[-1]]
        if all(len(c[0]) for c in columns):
            for b in walk_rule_arrays(q, columns):
                yield pa.record_batch([pa.array(c) for c in b], names=list(q.vars))
