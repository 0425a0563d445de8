"""Removal of long repeated strings by suffix arrays, over all documents.

Every window of 200 bytes names an anchor (see anchors). Windows can only be equal under equal anchors, so the corpus falls
apart into small texts, one per anchor, whose slices share no window with any other text. Slices that are the same byte for byte
are counted and kept once. What the slices of an anchor share to either side of it is cut out and again kept once with its
count; over these strings a suffix array is built by linear grouping, and windows whose neighbour there has a common
prefix of 200 bytes are repeats.

A text that is too long for one array, or for one task, falls apart once more: windows are told apart by where the anchor stands in
them, in bands, and by the bytes that all windows of a band hold, since equal windows agree in both. Bands become narrower until each
text is small; a band of one place leaves one string, the window. So every repeat is found in an array or by a count of
equal strings, however frequent the anchor.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anchors import GRAM, SPREAD, WINDOW, bands, runs
from .common import bitmap_of, discard, lean, marked, materialize, materialize_texts, total_partitions
from .suffix_sort import common_prefixes, suffix_array

#: Different slices of an anchor up to which they meet in one task.
HOT_SLICES = 2_000
#: Symbols of one suffix array.
ARRAY_SYMBOLS = 60_000
#: Widths of the bands by which a more frequent anchor's slices are dealt out, one after the other as far as it takes.
WIDTHS = (43, 11, 3, 1)

RUNS = "doc_id long, text_key long, anchor long, content long, start long, length long, place long"


def _raw(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "surrogatepass")


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    fields = [x.split() for x in schema.split(", ")]
    kinds = {"long": pa.int64(), "binary": pa.binary(), "string": pa.string(), "boolean": pa.bool_()}
    columns = list(zip(*rows, strict=True)) if rows else [()] * len(fields)
    return pa.record_batch([pa.array(list(c), kinds[k]) for c, (_, k) in zip(columns, fields, strict=True)], names=[n for n, _ in fields])


def text_runs(docs: DataFrame) -> DataFrame:
    """RUNS of every text of docs (doc_id, text_key, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, keys = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            parts: list[tuple] = []
            held = 0
            for i, text in enumerate(b.column(2)):
                found = runs(_raw(text.as_py()))
                parts.append((i, found))
                held += len(found[0])
                if held >= 200_000:
                    yield pack(ids, keys, parts)
                    parts, held = [], 0
            if parts:
                yield pack(ids, keys, parts)

    def pack(ids: np.ndarray, keys: np.ndarray, parts: list[tuple]) -> pa.RecordBatch:
        at = np.repeat([i for i, _ in parts], [len(f[0]) for _, f in parts]).astype(np.int64)
        columns = [np.concatenate([f[k] for _, f in parts]) for k in range(5)]
        return pa.record_batch([pa.array(ids[at]), pa.array(keys[at]), *(pa.array(c.view(np.int64)) for c in columns)], names=[x.split()[0] for x in RUNS.split(", ")])

    return docs.select("doc_id", "text_key", "text").mapInArrow(lean(run), RUNS)


def _shared(sides: list[bytes]) -> list[int]:
    """For each string the longest prefix that it shares with another one."""
    order = sorted(range(len(sides)), key=sides.__getitem__)
    out = [0] * len(sides)
    for i, j in zip(order, order[1:], strict=False):
        a, b = sides[i], sides[j]
        n = min(len(a), len(b))
        if a[:n] == b[:n]:
            k = n
        else:
            k = int((np.frombuffer(a, np.uint8, n) != np.frombuffer(b, np.uint8, n)).argmax())
        out[i], out[j] = max(out[i], k), max(out[j], k)
    return out


def repeated_windows(strings: list[bytes], places: list[int], times: list[int], width: int = SPREAD) -> list[np.ndarray]:
    """For each string, which of its windows also stand elsewhere: in another of the strings, or again if the string counts for several.

    strings: different, of one anchor, which stands at the places. They are joined, each closed by a symbol of its own, and ordered by
    a suffix array; if they are too long for one, their windows are taken apart by narrower bands.
    """
    out = [np.full(max(0, len(s) - WINDOW + 1), n > 1) for s, n in zip(strings, times, strict=True)]
    if len(strings) == 1:
        return out
    if sum(map(len, strings)) > ARRAY_SYMBOLS:
        width = max(1, width // 4)
        apart: dict[tuple, dict[bytes, list[tuple[int, int, int]]]] = {}
        for k, (s, p) in enumerate(zip(strings, places, strict=True)):
            for band, start, end, region in bands(s, p, width):
                apart.setdefault((band, region), {}).setdefault(s[start:end], []).append((k, start, p - start))
        for members in apart.values():
            counts = [sum(times[k] for k, _, _ in x) for x in members.values()]
            if sum(counts) > 1:
                for x, flags in zip(members.values(), repeated_windows(list(members), [x[0][2] for x in members.values()], counts, width), strict=True):
                    for k, start, _ in x:
                        out[k][start : start + len(flags)] |= flags
        return out
    text: list[int] = []
    begins = []
    for k, s in enumerate(strings):
        begins.append(len(text))
        text.extend(s)
        text.append(256 + k)
    order = suffix_array(text)
    near = common_prefixes(text, order)
    which = np.searchsorted(np.array(begins), np.arange(len(text)), side="right") - 1
    for r in np.flatnonzero(np.array(near) >= WINDOW).tolist():
        for s in (order[r - 1], order[r]):
            out[which[s]][s - begins[which[s]]] = True
    return out


def _spans(flags: np.ndarray) -> list[tuple[int, int]]:
    """Bytes covered by the flagged windows, as (start, end)."""
    at = np.flatnonzero(flags)
    if not len(at):
        return []
    cut = np.flatnonzero(np.diff(at) > WINDOW)
    return list(zip(at[np.r_[0, cut + 1]].tolist(), (at[np.r_[cut, len(at) - 1]] + WINDOW).tolist(), strict=True))


def anchor_repeats(slices: list[tuple[bytes, int, int]]) -> list[list[tuple[int, int]]]:
    """slices: (bytes, place of the anchor, times) of one anchor, all different. The covered spans of each."""
    right = _shared([s[p:] for s, p, _ in slices])
    left = _shared([s[: p + GRAM][::-1] for s, p, _ in slices])
    kept: dict[bytes, list[int]] = {}
    cut = []
    for i, (s, p, n) in enumerate(slices):
        a, z = (0, len(s)) if n > 1 else (p + GRAM - left[i], p + right[i])
        cut.append((a, z))
        if z - a >= WINDOW:
            kept.setdefault(s[a:z], []).append(i)
    out: list[list[tuple[int, int]]] = [[] for _ in slices]
    if kept:
        strings = list(kept)
        places = [slices[kept[s][0]][1] - cut[kept[s][0]][0] for s in strings]
        flags = repeated_windows(strings, places, [sum(slices[i][2] for i in kept[s]) for s in strings])
        for s, f in zip(strings, flags, strict=True):
            for i in kept[s]:
                out[i] = [(cut[i][0] + x, cut[i][0] + y) for x, y in _spans(f)]
    return out


CUT = "anchor long, doc_id long, text_key long, start long, place long, times long, slice binary"
SPANS = "doc_id long, text_key long, start long, end long"


def _slices(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """CUT: the bytes of the wanted slices (anchor, times, and doc_id, text_key, start, length, place of one occurrence)."""
    per = wanted.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("anchor", "start", "length", "place", "times")).alias("cuts"))
    per = per.select(F.col("doc_id").alias("_i"), F.col("text_key").alias("_k"), "cuts")
    texts = docs.dropDuplicates(["doc_id", "text_key"]).join(per, F.col("doc_id").eqNullSafe(F.col("_i")) & (F.col("text_key") == F.col("_k")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: list[tuple] = []
            for doc_id, key, text, cuts in zip(*(b.column(i) for i in range(4)), strict=True):
                raw = _raw(text.as_py())
                doc_id, key = doc_id.as_py(), key.as_py()
                rows += [(c["anchor"], doc_id, key, c["start"], c["place"], c["times"], raw[c["start"] : c["start"] + c["length"]]) for c in cuts.as_py()]
                if len(rows) >= 20_000:
                    yield _batch(rows, CUT)
                    rows = []
            yield _batch(rows, CUT)

    return texts.select("doc_id", "text_key", "text", "cuts").mapInArrow(lean(run), CUT)


def _array_spans(slices: DataFrame) -> DataFrame:
    """SPANS found by the suffix arrays of each anchor, for slices that occur once."""

    def settle(rows: list[tuple]) -> list[tuple]:
        found = anchor_repeats([(r[6], r[4], r[5]) for r in rows])
        return [(r[1], r[2], r[3] + a, r[3] + z) for r, spans in zip(rows, found, strict=True) if r[5] == 1 for a, z in spans]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group: list[tuple] = []
        for b in batches:
            done: list[tuple] = []
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if group and row[0] != group[0][0]:
                    done += settle(group)
                    group = []
                group.append(row)
            yield _batch(done, SPANS)
        if group:
            yield _batch(settle(group), SPANS)

    # the start orders what is cut alike; results do not depend on it
    dealt = slices.repartition(total_partitions(slices.sparkSession), "anchor").sortWithinPartitions("anchor", "doc_id", "start")
    return dealt.mapInArrow(lean(run), SPANS)


def _in_bands(slices: DataFrame, width: int) -> DataFrame:
    """CUT of the slices' bands, anchor being a hash of anchor, band and region, as far as a hash occurs again (and a few by chance).
    Texts of different regions may meet under one hash, which does no harm: arrays and counts go by the bytes."""

    def parts(row: tuple) -> Iterator[tuple]:
        anchor, doc_id, key, start, place, times, raw = row
        for band, a, z, region in bands(raw, place, width):
            seed = (anchor ^ (band + 1) * 0x9E3779B97F4A7C15) & (2**64 - 1)
            yield (int(np.uint64(xxhash.xxh3_64_intdigest(region, seed)).astype(np.int64)), doc_id, key, start + a, place - a, times, raw[a:z])

    def keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 2000):
                rows = zip(*(c.to_pylist() for c in b.slice(a, 2000).columns), strict=True)
                yield _batch([(p[0], p[5]) for row in rows for p in parts(row)], "anchor long, times long")

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 2000):
                rows = zip(*(c.to_pylist() for c in b.slice(a, 2000).columns), strict=True)
                yield _batch([p for row in rows for p in parts(row)], CUT)

    again = slices.mapInArrow(keys, "anchor long, times long").groupBy("anchor").agg(F.sum("times").alias("n")).where("n > 1")
    seen = bitmap_of(again, F.col("anchor"), "suffix-bitmap")
    return materialize(marked(slices.mapInArrow(whole, CUT), seen, F.col("anchor"), "_again").where("_again").drop("_again"), "suffix-bands")


def anchor_spans(slices: DataFrame, hot: int = HOT_SLICES, widths: tuple[int, ...] = WIDTHS) -> DataFrame:
    """SPANS of slices (CUT, different within an anchor) that occur once. Anchors of over `hot` slices are dealt out by bands; of equal
    bands one goes on, with the count of all."""
    many = materialize(slices.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > hot).select(F.col("anchor").alias("k")), "suffix-hot")
    if not widths or not many.limit(1).count():
        return _array_spans(slices)
    few = slices.join(many, F.col("anchor") == F.col("k"), "left_anti")
    parts = _in_bands(slices.join(many, F.col("anchor") == F.col("k"), "left_semi"), widths[0])
    one = F.min(F.struct("doc_id", "text_key", "start", "place")).alias("one")
    kinds = materialize(parts.groupBy("anchor", "slice").agg(F.sum("times").alias("times"), one).select("anchor", "one.*", "times", "slice"), "suffix-kinds")
    equal = kinds.where("times > 1").select(F.col("anchor").alias("_a"), F.col("slice").alias("_s"))
    same = parts.where("times = 1").join(equal, (F.col("anchor") == F.col("_a")) & (F.col("slice") == F.col("_s")), "left_semi")
    spans = same.select("doc_id", "text_key", "start", (F.col("start") + F.length("slice")).alias("end"))
    return _array_spans(few).unionByName(spans).unionByName(anchor_spans(kinds, hot, widths[1:]))


def repeat_spans(docs: DataFrame, hot: int = HOT_SLICES) -> DataFrame:
    """SPANS (may overlap) of all bytes of docs (doc_id, text_key, text) that a repeated window covers."""
    found = materialize_texts(text_runs(docs), "suffix-runs")
    anchors = found.groupBy("anchor").agg(F.count(F.lit(1)).alias("n"), F.min("content").alias("lo"), F.max("content").alias("hi")).where("n > 1")
    anchors = materialize(anchors.select(F.col("anchor").alias("k"), (F.col("lo") != F.col("hi")).alias("several")), "suffix-anchors")
    shared = materialize(found.join(anchors, F.col("anchor") == F.col("k")).drop("k"), "suffix-shared")
    discard(found, anchors)
    span = ["doc_id", "text_key", "start", (F.col("start") + F.col("length")).alias("end")]
    same = shared.where("not several").select(*span)

    several = shared.where("several")
    one = F.min(F.struct("doc_id", "text_key", "start", "length", "place")).alias("one")
    kinds = materialize(several.groupBy("anchor", "content").agg(F.count(F.lit(1)).alias("times"), one).select("anchor", "content", "times", "one.*"), "suffix-kinds")
    copies = kinds.where("times > 1").select(F.col("anchor").alias("a"), F.col("content").alias("c"))
    copied = several.join(copies, (F.col("anchor") == F.col("a")) & (F.col("content") == F.col("c")), "left_semi").select(*span)
    slices = materialize_texts(_slices(docs, kinds), "suffix-slices")
    return same.unionByName(copied).unionByName(anchor_spans(slices, hot))


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT_SLICES) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept_text (bytes) for every row of docs.

    A byte goes if a 200-byte string over it also starts elsewhere, in the same text too; strings are judged on the input. A null
    text is empty. Rows that repeat id and text are occurrences of their own and fare alike. Texts under 200 bytes
    lose nothing; texts may be of any length. Other columns are not read. An empty table gives an empty result.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0)).alias("text_key"), F.col(text_col).alias("text"))
    spans = repeat_spans(rows, hot).groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("start", "end")).alias("spans"))
    spans = materialize(spans, "suffix-spans").select(F.col("doc_id").alias("_i"), F.col("text_key").alias("_k"), "spans")
    joined = rows.join(spans, F.col("doc_id").eqNullSafe(F.col("_i")) & (F.col("text_key") == F.col("_k")), "left")
    schema = f"{RESULT}, kept_text binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for doc_id, text, spans in zip(*(b.column(i) for i in range(3)), strict=True):
                raw, merged = _raw(text.as_py()), []
                for s in sorted((s["start"], s["end"]) for s in spans.as_py() or ()):
                    if merged and s[0] <= merged[-1][1]:
                        merged[-1][1] = max(merged[-1][1], s[1])
                    else:
                        merged.append([*s])
                kept, at = [], 0
                for a, z in merged:
                    kept.append(raw[at:a])
                    at = z
                left = b"".join([*kept, raw[at:]])
                out.append((doc_id.as_py(), len(raw), len(raw) - len(left), len(merged), hashlib.sha256(left).hexdigest(), left))
            yield _batch(out, schema)

    return joined.select("doc_id", "text", "spans").mapInArrow(lean(run), schema)
