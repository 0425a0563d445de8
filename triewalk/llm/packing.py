"""Packing token sequences into windows of a fixed capacity by multiway differencing (Karmarkar-Karp).

A document longer than the capacity is cut into full windows and a rest; a rest is cut once more where it is long,
into a large piece and a small one. Pieces are dealt to groups of a bounded number by hash; in each group differencing
spreads the pieces over the least number of windows that could hold them, and over one more as long as a window is over its capacity.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, materialize_texts
from .tokens import encoder

CAPACITY = 2048
#: Mean number of pieces of a group.
GROUP = 3000
#: Of a rest longer than the first number of ids, so many at its end become a piece of their own: small pieces even out the windows.
#: (256, 48) leaves hardly any padding; None cuts documents at the capacity alone.
SPLIT = (256, 48)


def difference(sizes: np.ndarray, k: int) -> np.ndarray:
    """The window, 0 to k-1, of each of the sizes: partial partitions (one a size at first) are merged, the two of the widest
    spread first, the largest windows of one with the smallest of the other.

    A merge keeps only which windows met, so the windows of the sizes are read off from the last merge down.
    Memory: merges x k small integers. Ties go by the order of creation.
    """
    n = len(sizes)
    if k <= 1 or n == 0:
        return np.zeros(n, dtype=np.int64)
    loads: dict[int, np.ndarray] = {}
    heap = []
    for i, s in enumerate(sizes.tolist()):
        heap.append((-s, i))
    heapq.heapify(heap)
    merges: list[tuple[int, int, int, np.ndarray]] = []
    nxt = n

    def load(i: int) -> np.ndarray:
        if i < n:
            out = np.zeros(k, dtype=np.int64)
            out[0] = sizes[i]
            return out
        return loads.pop(i)

    # a partition keeps its windows sorted by load, largest first
    while len(heap) > 1:
        _, a = heapq.heappop(heap)
        _, b = heapq.heappop(heap)
        both = load(a) + load(b)[::-1]
        order = np.argsort(-both, kind="stable")
        merges.append((nxt, a, b, order.astype(np.int32)))
        both = both[order]
        both -= both[-1]
        loads[nxt] = both
        heapq.heappush(heap, (-int(both[0]), nxt))
        nxt += 1
    at = {heap[0][1]: np.arange(k, dtype=np.int32)}
    window = np.zeros(n, dtype=np.int64)
    for made, a, b, order in reversed(merges):
        final = np.empty(k, dtype=np.int32)
        final[order] = at.pop(made)
        at[a], at[b] = final, final[::-1]
        for i in (a, b):
            if i < n:
                window[i] = at.pop(i)[0]
    if n == 1:
        window[0] = 0
    return window


def pack_sizes(sizes: np.ndarray, capacity: int = CAPACITY) -> np.ndarray:
    """The window of each size (all at most capacity); the number of windows rises until none is over its capacity."""
    k = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        window = difference(sizes, k)
        if not len(sizes) or np.bincount(window, weights=sizes, minlength=k).max() <= capacity:
            return window
        k += 1


def cut(n: int, capacity: int = CAPACITY, split: tuple[int, int] | None = SPLIT) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces."""
    out = [(a, capacity) for a in range(0, n - capacity + 1, capacity)]
    start = len(out) * capacity
    rest = n - start
    if split and rest > split[0]:
        out += [(start, rest - split[1]), (n - split[1], split[1])]
    elif rest:
        out.append((start, rest))
    return out


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, doc_pieces long, row_no long"


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, split: tuple[int, int] | None = SPLIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a piece of each document, ids encoded by the tokenizer with the end id appended."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer).encode
        for b in batches:
            rows = []
            for doc_id, row_no, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                ids = memoryview(encode(text.as_py()))
                n = len(ids) // 4
                spans = cut(n, capacity, split)
                rows += [(doc_id, a, m, zlib.crc32(ids[4 * a : 4 * (a + m)]), n, len(spans), row_no) for a, m in spans]
            columns = list(zip(*rows, strict=True)) if rows else [()] * 7
            yield pa.record_batch([pa.array(list(c), pa.int64()) for c in columns], names=[x.split()[0] for x in PIECES.split(", ")])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.monotonically_increasing_id().alias("row_no"), F.col(text_col).alias("text"))
    return rows.mapInArrow(lean(run), PIECES)


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, group: int = GROUP, split: tuple[int, int] | None = SPLIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, doc_pieces: one row a piece; doc_pieces: of its document.

    Null and empty texts have the end id alone, one piece. Rows that repeat an id are packed as rows of their own. A full
    piece is a sequence by itself. Offsets of a sequence are gapless from 0. An empty table gives an empty result.
    Groups hold about `group` pieces each, by a hash of (row, start), so a very long document spreads over many. Other columns are not read.
    """
    cut_up = materialize_texts(pieces(docs, tokenizer, capacity, split, id_col, text_col), "pack-pieces")
    groups = max(1, round(cut_up.count() / group))
    keyed = cut_up.withColumn("grp", F.pmod(F.xxhash64("row_no", "start"), F.lit(groups)))

    def assign(key: tuple, one: pd.DataFrame) -> pd.DataFrame:
        one = one.sort_values(["length", "row_no", "start"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
        sizes = one["length"].to_numpy()
        full = int((sizes == capacity).sum())
        window = np.concatenate([np.arange(full), full + pack_sizes(sizes[full:], capacity)])
        one["sequence_id"] = window + (int(key[0]) << 24)
        one["offset"] = one.groupby("sequence_id")["length"].cumsum() - one["length"]
        return one[["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "doc_pieces"]]

    return keyed.groupBy("grp").applyInPandas(assign, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, doc_pieces long")
