"""The join in one shuffle: rows are copied to the cells of a grid over the variables, and each cell is walked by itself.

A row goes to every cell that agrees with the hashes of its own values, so each answer arises in exactly one cell. Rows of one cell are packed
before they are sent: the shuffle moves a value for many rows. A cell is sorted where it is walked and is the unit of memory. The last
variable's values leave a cell as lists, a row a prefix, and are made rows by Spark.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernel.walk import ColumnTrie, count_answers, walk_batches
from ..plans.rewrite import KeyFrame

#: Rows of an atom that a task gathers before it packs them by cell.
PACK_ROWS = 1 << 20
_KINDS = ("u1", "u2", "u4", "u8")
_WHOLE = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def whole_numbers(frames: list[KeyFrame]) -> bool:
    """Whether the kernel can take the keys as they are; other types go through a dictionary first."""
    return all(isinstance(f.dataType, _WHOLE) for fr in frames for f in fr.df.schema.fields)


def pack(columns: list[np.ndarray]) -> bytes:
    """Columns of whole numbers (at least one row) as one value: each its least number, then distances to it in as few bytes as hold them."""
    out = [struct.pack("<q", len(columns[0]))]
    for c in columns:
        least = int(c.min())
        kind = next(i for i, k in enumerate(_KINDS) if int(c.max()) - least <= np.iinfo(k).max)
        out.append(struct.pack("<qB", least, kind))
        out.append((c.view(np.uint64) - np.array(least).view(np.uint64)).astype(_KINDS[kind]).tobytes())
    return b"".join(out)


def unpack(value: bytes | pa.Buffer, width: int) -> list[np.ndarray]:
    """The columns of a packed value."""
    n, at, out = struct.unpack_from("<q", value)[0], 8, []
    for _ in range(width):
        least, kind = struct.unpack_from("<qB", value, at)
        far = np.frombuffer(value, dtype=f"<{_KINDS[kind]}", count=n, offset=at + 9)
        out.append((far.astype(np.uint64) + np.array(least).view(np.uint64)).view(np.int64))
        at += 9 + far.nbytes
    return out


def pack_by_cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(cell, values...) rows as (cell, packed values), about PACK_ROWS rows at a time."""

    def packed(held: list[list[np.ndarray]]) -> pa.RecordBatch:
        cell, *columns = (np.concatenate(c) for c in zip(*held, strict=True))
        order = np.argsort(cell.astype(np.uint16) if cell.max() < 1 << 16 else cell, kind="stable")
        cell, columns = cell[order], [c[order] for c in columns]
        edges = np.r_[np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]), len(cell)]
        values = [pack([c[a:z] for c in columns]) for a, z in zip(edges[:-1], edges[1:], strict=True)]
        return pa.record_batch([pa.array(cell[edges[:-1]], pa.int32()), pa.array(values, pa.binary())], names=["_fixed", "packed"])

    held, n = [], 0
    for b in batches:
        if b.num_rows:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            n += b.num_rows
        if n >= PACK_ROWS:
            yield packed(held)
            held, n = [], 0
    if held:
        yield packed(held)


def assign(frames: list[KeyFrame], order: list[str], shares: dict[str, int]) -> DataFrame:
    """(cell, atom, packed) rows of all atoms: many rows of an atom that go to the same cells are one value."""
    step, at = {}, 1
    for v in order:
        step[v], at = at, at * shares.get(v, 1)
    out = None
    for i, f in enumerate(frames):
        fixed = F.lit(0)
        for v in f.vars:
            if shares.get(v, 1) > 1:
                fixed = fixed + F.pmod(F.xxhash64(F.col(v).cast("long")), F.lit(shares[v])).cast("int") * step[v]
        free = [0]
        for v in order:
            if v not in f.vars:
                free = [a + b * step[v] for a in free for b in range(shares.get(v, 1))]
        cell = (F.explode(F.array(*(F.lit(x) for x in free))) if len(free) > 1 else F.lit(free[0])).alias("_free")
        part = f.df.select(fixed.alias("_fixed"), *(F.col(v).cast("long").alias(f"c{d}") for d, v in enumerate(f.vars)))
        part = part.mapInArrow(pack_by_cell, "_fixed int, packed binary").select("_fixed", cell, F.lit(i).cast("int").alias("atom"), "packed")
        part = part.select((F.col("_fixed") + F.col("_free")).cast("int").alias("cell"), "atom", "packed")
        out = part if out is None else out.unionByName(part)
    return out


def participants(atoms: list[tuple[str, ...]], order: list[str]) -> list[list[tuple[int, int]]]:
    return [[(i, vs.index(v)) for i, vs in enumerate(atoms) if v in vs] for v in order]


def as_lists(*columns: np.ndarray, most: int) -> list[pa.Array]:
    """A block of prefixes, numbers of values and values as Arrow columns; a prefix of many values takes several rows, of none no row."""
    *prefix, n, values = columns
    past = np.cumsum(n)
    edges = np.unique(np.r_[0, past, np.arange(0, len(values), most)])
    row = np.searchsorted(past, edges[:-1], side="right")
    return [*(pa.array(p[row]) for p in prefix), pa.ListArray.from_arrays(pa.array(edges, pa.int32()), pa.array(values))]


def run_cells(frames: list[KeyFrame], order: list[str], shares: dict[str, int], batch_rows: int = 1 << 16, measure: str | None = None) -> DataFrame:
    """All bindings as longs; measure="costs": per cell the rows expanded at each level instead (cell, level, cost); "count": per cell
    the number of bindings (n), none of them made."""
    cells = math.prod(shares.get(v, 1) for v in order)
    rows = assign(frames, order, shares)
    arities, levels = [len(f.vars) for f in frames], participants([f.vars for f in frames], order)
    # a cell number is a partition number, so cells never meet in one task
    dealt = rows.repartitionById(cells, "cell") if hasattr(rows, "repartitionById") else rows.repartition(cells, "cell").sortWithinPartitions("cell")
    lists = measure is None and len(order) > 1

    def one(cell: int, held: list[list[list[np.ndarray]]]) -> Iterator[pa.RecordBatch]:
        if any(not h for h in held):
            return
        tries = [ColumnTrie.of([np.concatenate([b[d] for b in h]) for d in range(a)]) for h, a in zip(held, arities, strict=True)]
        if measure == "count":
            yield pa.record_batch([pa.array([count_answers(tries, levels, batch_rows)], pa.int64())], names=["n"])
            return
        costs = np.zeros(len(order), dtype=np.int64)
        for columns in walk_batches(tries, levels, batch_rows, costs if measure else None, lists=lists):
            if lists:
                yield pa.record_batch(as_lists(*columns, most=batch_rows), names=order)
            elif measure is None:
                yield pa.record_batch([pa.array(c) for c in columns], names=order)
        if measure == "costs":
            yield pa.record_batch([pa.array([cell] * len(order), pa.int64()), pa.array(np.arange(len(order))), pa.array(costs)], names=["cell", "level", "cost"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, done = None, [[] for _ in arities], set()
        for b in batches:
            for cell, atom, packed in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                if at is not None and cell != at:
                    yield from one(at, held)
                    held = [[] for _ in arities]
                    done.add(at)
                at = cell
                if at in done:
                    raise ValueError(f"rows of cell {at} do not follow each other")
                held[atom].append(unpack(packed.as_buffer(), arities[atom]))
        if at is not None:
            yield from one(at, held)

    schema = "n long" if measure == "count" else "cell long, level long, cost long" if measure == "costs" else ", ".join(f"`{v}` long" for v in order)
    if lists:
        fields = [*(T.StructField(v, T.LongType(), False) for v in order[:-1]), T.StructField(order[-1], T.ArrayType(T.LongType(), False), False)]
        out = dealt.mapInArrow(run, T.StructType(fields))
        return out.select(*(F.col(f"`{v}`") for v in order[:-1]), F.explode(F.col(f"`{order[-1]}`")).alias(order[-1]))
    return dealt.mapInArrow(run, schema)
