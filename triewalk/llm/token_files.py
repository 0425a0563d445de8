"""Token ids in Arrow files of fixed-size lists: equal-length sequences with masks, addressed without copying.

Documents are dealt to ranges of doc_id and encoded in order; each range becomes one shard of two Arrow files:
`ids`, whose rows are sequences of SEQUENCE ids (16 bits each if the vocabulary fits, else 32) with a bit mask of the same length, and `docs`, which says where each document
lies in the shard. All ids of a shard run on from row to row; only its last row is padded (mask false). The file of
a shard is written under a name of its attempt and then renamed, so a repeated task leaves the same file.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, scratch_path, text_batches, total_partitions
from .tokens import encoder

SEQUENCE = 1024
ROWS_A_BATCH = 256



def ids_schema(vocabulary: int) -> pa.Schema:
    return pa.schema([("ids", pa.list_(pa.uint16() if vocabulary <= 1 << 16 else pa.uint32(), SEQUENCE)), ("mask", pa.list_(pa.bool_(), SEQUENCE))])


DOCS_SCHEMA = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


def _store(uri: str):
    """The file system and path of a URI that pyarrow knows (file, hdfs, s3, gs), or of a plain path."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri.replace("file:///", "/").replace("file:/", "/") if uri.startswith("file:") else uri)


class ShardWriter:
    """Writes one shard; add() takes a document's ids as bytes, close() returns (docs, ids)."""

    def __init__(self, folder: str, shard: int, vocabulary: int):
        self.store, path = _store(folder)
        self.schema = ids_schema(vocabulary)
        self.kind = self.schema.field("ids").type.value_type.to_pandas_dtype()
        self.store.create_dir(path, recursive=True)
        self.final = [f"{path}/{kind}-{shard:06d}.arrow" for kind in ("ids", "docs")]
        self.parts = [f"{x}.{uuid.uuid4().hex}.part" for x in self.final]
        self.sinks = [self.store.open_output_stream(p) for p in self.parts]
        self.ids, self.docs = pa.ipc.new_file(self.sinks[0], self.schema), pa.ipc.new_file(self.sinks[1], DOCS_SCHEMA)
        self.rest, self.held, self.total, self.index = [], 0, 0, []
        self.n_docs = 0

    def add(self, doc_id: int | None, ids: bytes) -> None:
        n = len(ids) // 4
        self.index.append((doc_id, self.total, n))
        self.total += n
        self.n_docs += 1
        self.rest.append(np.frombuffer(ids, dtype="<u4").astype(self.kind))
        self.held += n
        if self.held >= SEQUENCE * ROWS_A_BATCH:
            self._flush(False)
        if len(self.index) >= 10_000:
            self._flush_index()

    def _flush(self, last: bool) -> None:
        flat = np.concatenate([np.empty(0, self.kind), *self.rest])
        batch, padded = SEQUENCE * ROWS_A_BATCH, 0
        if last:
            padded = -len(flat) % SEQUENCE
            flat = np.concatenate([flat, np.zeros(padded, self.kind)])
        # only the last batch of a shard may be short: readers find a place by division
        upto = len(flat) if last else len(flat) // batch * batch
        for a in range(0, upto, batch):
            end = min(upto, a + batch)
            self._rows(flat[a:end], padded if end == len(flat) else 0)
        self.rest, self.held = [flat[upto:].copy()], len(flat) - upto

    def _rows(self, flat: np.ndarray, padded: int) -> None:
        mask = np.ones(len(flat), bool)
        mask[len(flat) - padded :] = False
        self.ids.write_batch(pa.record_batch([pa.FixedSizeListArray.from_arrays(pa.array(x), SEQUENCE) for x in (flat, mask)], schema=self.schema))

    def _flush_index(self) -> None:
        if self.index:
            self.docs.write_batch(pa.record_batch([pa.array(list(x), pa.int64()) for x in zip(*self.index, strict=True)], schema=DOCS_SCHEMA))
            self.index = []

    def close(self) -> tuple[int, int]:
        self._flush(True)
        self._flush_index()
        for w, sink, part, final in zip((self.ids, self.docs), self.sinks, self.parts, self.final, strict=True):
            w.close()
            sink.close()
            self.store.move(part, final)
        return self.n_docs, self.total


class ShardReader:
    """Random access to a shard: rows by number, documents by (start, length), both as views of the mapped file."""

    def __init__(self, folder: str, shard: int):
        self.store, path = _store(folder)
        self.ids = pa.ipc.open_file(self._open(f"{path}/ids-{shard:06d}.arrow"))
        self.docs = pa.ipc.open_file(self._open(f"{path}/docs-{shard:06d}.arrow"))
        self._at, self._flat = -1, None

    def _open(self, path: str):
        from pyarrow import fs

        return pa.memory_map(path) if isinstance(self.store, fs.LocalFileSystem) else self.store.open_input_file(path)

    def _batch(self, k: int) -> np.ndarray:
        if k != self._at:
            self._at, self._flat = k, self.ids.get_batch(k).column(0).flatten().to_numpy()
        return self._flat

    def row(self, k: int) -> np.ndarray:
        a = k % ROWS_A_BATCH * SEQUENCE
        return self._batch(k // ROWS_A_BATCH)[a : a + SEQUENCE]

    def span(self, start: int, n: int) -> list[np.ndarray]:
        """The ids of [start, start + n) as one view a batch: every batch but the last of a shard has the same number of rows."""
        size, out = SEQUENCE * ROWS_A_BATCH, []
        while n > 0:
            k, a = divmod(start, size)
            take = min(n, size - a)
            out.append(self._batch(k)[a : a + take])
            start, n = start + take, n - take
        return out

    def documents(self) -> Iterator[tuple[int | None, int, int]]:
        for k in range(self.docs.num_record_batches):
            yield from zip(*(c.to_pylist() for c in self.docs.get_batch(k).columns), strict=True)


def write_token_files(docs: DataFrame, folder: str, tokenizer: str, shards: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> list[tuple[int, int, int]]:
    """Writes all rows of docs in ascending order of id (nulls first) and returns (shard, documents, ids), one a shard.

    A null text is empty: its end id alone. Rows that repeat an id stand side by side. An empty table writes
    nothing. Shards: by default the number of shuffle partitions. The list has a row a shard, not a document.
    """
    shards = shards or total_partitions(docs.sparkSession)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, shard, out = encoder(tokenizer).encode, TaskContext.get().partitionId(), None
        size = encoder(tokenizer).tokenizer.get_vocab_size()
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                out = out or ShardWriter(folder, shard, size)
                out.add(doc_id, encode(text.as_py()))
        if out:
            yield pa.record_batch([pa.array([x], pa.int64()) for x in (shard, *out.close())], names=["shard", "docs", "ids"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    dealt = rows.repartitionByRange(shards, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    with text_batches(docs.sparkSession):
        return sorted(tuple(r) for r in dealt.mapInArrow(lean(write), "shard long, docs long, ids long").collect())


def read_token_files(spark, folder: str, manifest: list[tuple[int, int, int]]) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, read from the files; start counts the ids of all documents before."""
    starts, total = [], 0
    for shard, _, ids in manifest:
        starts.append((shard, total))
        total += ids

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for shard, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                shard_file, rows = ShardReader(folder, shard), []
                for doc_id, start, n in shard_file.documents():
                    crc = 0
                    for view in shard_file.span(start, n):
                        crc = zlib.crc32(view.astype("<u4"), crc)
                    rows.append((doc_id, base + start, n, crc))
                    if len(rows) >= 10_000:
                        yield _rows(rows)
                        rows = []
                yield _rows(rows)

    files = spark.createDataFrame(starts, "shard long, base long").repartition(max(1, len(starts)), "shard") if starts else spark.createDataFrame([], "shard long, base long")
    return files.mapInArrow(lean(read), "doc_id long, start long, n_tokens long, ids_crc32 long")


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[]] * 4
    return pa.record_batch([pa.array(list(c), pa.int64()) for c in columns], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def token_file_digests(docs: DataFrame, tokenizer: str, shards: int | None = None) -> DataFrame:
    """Writes docs to files in the shared folder and reads the digests of its documents back from them."""
    folder = scratch_path(docs.sparkSession, "token-files")
    return read_token_files(docs.sparkSession, folder, write_token_files(docs, folder, tokenizer, shards))
