"""SimHash near-dedup by Golay-code fuzzy hashing.

A text's shingles vote on the bits of its fingerprint. Fingerprints that differ in few bits are found through keys: some bits
taken as they are, and 23 more decoded to nearby codewords of the Golay code, which gives one to six keys and
tolerates two errors. Two plans of keys:

- exact: for at most three differing bits of 64. Of four 16-bit segments one has no error; of the halves of the other 48
  bits one has at most one. Eight tables of (segment, half's codewords) therefore meet every such pair.
- sampled: for texts of a given share of common shingles. Wide fingerprints, many tables of bits drawn by a fixed rule. What
  these leave apart is met without chance: sets of so large a common share have a shingle in common among the first few of
  each in any one order, so texts of different components that share such a shingle are compared too, every pair of them.

Rows with a common key meet in one task, which compares fingerprints in blocks and passes on a least spanning forest of
the pairs that are close enough: fewer links than rows, and no link between components is lost. A key of more rows than a block is
dealt out again, as pairs of blocks, each a task's work by itself. Texts that share a frequent shingle are compared in such
blocks too, on their whole sets, and a block passes on a forest of pairs that are verified. Components are then formed by joins.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import golay
from .common import bitmap_of, discard, lean, marked, materialize, materialize_texts, text_batches, total_partitions, without_ids
from .components import components

SEED = 42
MAX_BITS = 3
#: The sampled plan: 64-bit words of a fingerprint, tables, bits taken as they are, and most differing bits of the first 64.
WIDE, TABLES, PLAIN_BITS, WIDE_BITS = 4, 24, 8, 17
#: Most differing bits of all WIDE words for which a candidate of the sampled plan is compared on its shingles; what that leaves out is met by prefixes.
WIDE_ALL = 52
SHINGLE, SIMILARITY = 5, 0.8
#: Common shingles stand last in the order of prefixes: the most frequent ones in one of so many texts. Only the order, never a result, depends on them.
COMMON, COMMON_ONE_IN = 1 << 15, 16
#: Rows that a block of comparisons holds on each side.
BLOCK = 2048
#: Rows of a key up to which they meet where the key's rows are dealt to; keys of more are dealt out in pairs of blocks.
HOT_KEY = 1 << 14
#: Texts of a shingle up to which they are passed on as pairs; those of a more frequent one are compared in blocks, which hold so many shingles at most on a side.
HOT_SHINGLE, BLOCK_SHINGLES = 64, 1 << 20

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)]


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    """XXH64 (seed 42) of every run of `size` words, repeats included; of the whole sequence if it has fewer; none for no words."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return np.empty(0, dtype=np.uint64)
    line, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= size:
        return np.array([digest(line, SEED)], dtype=np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1)
    begins = ends - np.fromiter(map(len, words), dtype=np.int64, count=len(words)) - 1
    spans = zip(begins[: len(words) - size + 1].tolist(), (ends[size - 1 :] - 1).tolist(), strict=True)
    return np.array([digest(line[a:z], SEED) for a, z in spans], dtype=np.uint64)


def votes(hashes: np.ndarray) -> int:
    """A bit is 1 if set in over half of the hashes; 0 for none."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, dtype=np.int64)
    for a in range(0, len(hashes), 1 << 16):
        part = hashes[a : a + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def spread(hashes: np.ndarray, k: int) -> np.ndarray:
    """The k-th further hash of each shingle (k = 0: the hash itself), by multiply and xor-shift."""
    if k == 0:
        return hashes
    x = (hashes ^ (hashes >> np.uint64(31))) * _ODD[k - 1]
    return x ^ (x >> np.uint64(29))


def fingerprints(docs: DataFrame, size: int, words: int, distinct: bool, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and fp0, fp1, ...: `words` 64-bit words of each text's fingerprint (as signed long); distinct: each shingle votes once."""
    names = ["doc_id", *(f"fp{k}" for k in range(words))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = np.zeros((b.num_rows, words), dtype=np.uint64)
            for i, text in enumerate(b.column(1)):
                h = shingle_hashes(text.as_py(), size)
                h = np.unique(h) if distinct else h
                for k in range(words):
                    out[i, k] = votes(spread(h, k))
            yield pa.record_batch([b.column(0), *(pa.array(out[:, k].view(np.int64)) for k in range(words))], names=names)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(lean(run), ", ".join(f"{n} long" for n in names))


def exact_keys(fp: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, key) of each of the eight tables over fp (n, 1)."""
    x = fp[:, 0]
    for i in range(4):
        plain = (x >> np.uint64(16 * i)) & np.uint64(0xFFFF)
        low = x & np.uint64((1 << (16 * i)) - 1)
        high = (x >> np.uint64(16 * i + 16)) << np.uint64(16 * i) if i < 3 else np.zeros_like(x)
        rest = high | low
        for j in range(2):
            half = (rest >> np.uint64(24 * j)) & np.uint64((1 << golay.BITS) - 1)
            rows, code = golay.keys(half)
            yield rows, (np.int64(2 * i + j) << np.int64(28)) | (plain[rows].astype(np.int64) << np.int64(12)) | code.astype(np.int64)


def sampled_keys(fp: np.ndarray, tables: int = TABLES, plain_bits: int = PLAIN_BITS) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(rows, key) of each table over fp (n, words): the bits of a table are drawn from all bits by a seeded permutation."""
    bits = np.unpackbits(fp.view(np.uint8).reshape(len(fp), -1), axis=1, bitorder="little")
    rng = np.random.default_rng(SEED)
    power = 1 << np.arange(golay.BITS, dtype=np.int64)
    for t in range(tables):
        drawn = rng.permutation(bits.shape[1])[: golay.BITS + plain_bits]
        rows, code = golay.keys(bits[:, drawn[: golay.BITS]] @ power)
        plain = bits[:, drawn[golay.BITS :]] @ power[:plain_bits]
        yield rows, (np.int64(t) << np.int64(40)) | (plain[rows] << np.int64(12)) | code.astype(np.int64)


def key_rows(reps: DataFrame, plan: str, words: int, carried: int) -> DataFrame:
    """(key, id, fp0...) for every key of every row of reps (id, fp0, ...); `carried` words go along for comparison."""
    make = exact_keys if plan == "exact" else sampled_keys
    schema = "key long, id long, " + ", ".join(f"fp{k} long" for k in range(carried))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 4096):
                part = b.slice(a, 4096)
                ids = part.column(0).to_numpy(zero_copy_only=False)
                fp = np.stack([part.column(1 + k).to_numpy(zero_copy_only=False) for k in range(words)], axis=1).view(np.uint64)
                for rows, key in make(fp):
                    yield pa.record_batch([pa.array(key), pa.array(ids[rows]), *(pa.array(fp[rows, k].view(np.int64)) for k in range(carried))], names=["key", "id", *(f"fp{k}" for k in range(carried))])

    return reps.select("id", *(f"fp{k}" for k in range(words))).mapInArrow(run, schema)


def _distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits of each row of a and each of b."""
    return sum(np.bitwise_count(a[:, None, k] ^ b[None, :, k]).astype(np.int16) for k in range(a.shape[1]))


class Forest:
    """Union-find over the rows of one bucket."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.root(i), self.root(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        return True


def close_pairs(fp: np.ndarray, most: int) -> list[tuple[int, int]]:
    """A least spanning forest of the pairs of rows at most `most` bits apart, block by block: each pair is looked at,
    a block's pairs are taken in order of distance, and what is held is a forest and one block."""
    n, edges = len(fp), []
    for a in range(0, n, BLOCK):
        for b in range(a, n, BLOCK):
            d = _distances(fp[a : a + BLOCK], fp[b : b + BLOCK])
            i, j = np.nonzero(d <= most)
            keep = a + i < b + j
            edges.append(np.stack([d[i[keep], j[keep]].astype(np.int64), a + i[keep], b + j[keep]], axis=1))
            if sum(map(len, edges)) > 1_000_000:
                edges = [_spanning(np.concatenate(edges), n)]
    return [(int(i), int(j)) for _, i, j in _spanning(np.concatenate(edges), n)] if edges else []


def _spanning(edges: np.ndarray, n: int) -> np.ndarray:
    edges = edges[np.lexsort((edges[:, 2], edges[:, 1], edges[:, 0]))]
    forest = Forest(n)
    return edges[[forest.join(i, j) for i, j in edges[:, 1:].tolist()]] if len(edges) else edges


def settle_buckets(table: np.ndarray, carried: int, most: int) -> np.ndarray:
    """Links (a, b) within whole buckets. table: key, id, fp0, ..., sorted by key."""
    table = table[np.lexsort((table[:, 1], table[:, 0]))]  # by id in a bucket, so that buckets of the same rows choose the same links
    key = table[:, 0]
    new = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    size = np.diff(np.r_[new, len(key)])
    ids, fp = table[:, 1], np.ascontiguousarray(table[:, 2:]).view(np.uint64)
    found, near = [], []
    # small buckets, all at once: each row against the next ones of its bucket
    last = np.repeat(new + size, size)
    at = np.flatnonzero(np.repeat(size <= 16, size))
    for step in range(1, 16):
        at = at[at + step < last[at]]
        if not len(at):
            break
        d = sum(np.bitwise_count(fp[at, k] ^ fp[at + step, k]).astype(np.int16) for k in range(carried))
        hit = d <= most
        near.append(np.stack([d[hit].astype(np.int64), at[hit], at[hit] + step], axis=1))
    if near:
        found.append(ids[_spanning(np.concatenate(near), len(table))[:, 1:]])
    for a, n in zip(new[size > 16].tolist(), size[size > 16].tolist(), strict=True):
        pairs = np.array(close_pairs(fp[a : a + n], most), dtype=np.int64).reshape(-1, 2)
        found.append(ids[a + pairs])
    return np.concatenate(found) if found else np.empty((0, 2), np.int64)


def link_batch(links: np.ndarray, hot: bool = False) -> pa.RecordBatch:
    """Links as rows (a, b, hot), each once, the lesser id first."""
    links = np.unique(np.sort(links[links[:, 0] != links[:, 1]], axis=1), axis=0) if not hot else links
    return pa.record_batch([pa.array(links[:, 0].copy()), pa.array(links[:, 1].copy()), pa.array(np.full(len(links), hot))], names=["a", "b", "hot"])


def bucket_links(rows: DataFrame, carried: int, most: int, hot_key: int = HOT_KEY) -> DataFrame:
    """(a, b) links between ids of rows (key, id, fp0, ...) that share a key, distinct; they may be found again under several keys.

    A key of more than hot_key rows is only named by the task that meets it, which holds none of its rows beyond that number;
    its rows are dealt out by block_units.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, hot = np.empty((0, 2 + carried), np.int64), None
        for b in batches:
            for a in range(0, b.num_rows, 1 << 16):
                table = np.stack([c.to_numpy(zero_copy_only=False) for c in b.slice(a, 1 << 16).columns], axis=1)
                held = np.concatenate([held, table[table[:, 0] != hot] if hot is not None else table])
                if len(held) < 100_000 and not (len(held) > hot_key and held[-hot_key - 1, 0] == held[-1, 0]):
                    continue
                end = int(np.searchsorted(held[:, 0], held[-1, 0]))  # the last bucket may go on
                if end:
                    yield from whole(held[:end])
                    held = held[end:]
                if len(held) > hot_key:
                    hot = held[0, 0]
                    yield link_batch(np.array([[hot, hot]]), True)
                    held = held[:0]
        if len(held):
            yield from whole(held)

    def whole(table: np.ndarray) -> Iterator[pa.RecordBatch]:
        new = np.flatnonzero(np.r_[True, table[1:, 0] != table[:-1, 0]])
        size = np.diff(np.r_[new, len(table)])
        large = size > hot_key
        if large.any():
            key = table[new[large], 0]
            yield link_batch(np.stack([key, key], axis=1), True)
            table = table[np.repeat(~large, size)]
        if len(table):
            yield link_batch(settle_buckets(table, carried, most))

    dealt = rows.repartition(total_partitions(rows.sparkSession), "key").sortWithinPartitions("key")
    found = materialize(dealt.mapInArrow(lean(run), LINKS).distinct(), "bucket-links")
    links, hot = found.where("not hot").select("a", "b"), found.where("hot").select(F.col("a").alias("key"))
    if not hot.limit(1).count():
        return links

    names = ["key", "id", *(f"fp{k}" for k in range(carried))]
    there = materialize(rows.join(hot, "key", "left_semi").select(*names), "bucket-hot")

    def compare(unit: list[np.ndarray]) -> np.ndarray:
        side, ids, fp = unit[0], unit[1], np.ascontiguousarray(np.stack(unit[2:], axis=1)).view(np.uint64)
        two = len(np.unique(side)) > 1
        x, y = (np.flatnonzero(side == side.min()), np.flatnonzero(side == side.max()))
        edges = []
        for a in range(0, len(x), BLOCK):
            for b in range(0, len(y), BLOCK):
                d = _distances(fp[x[a : a + BLOCK]], fp[y[b : b + BLOCK]])
                i, j = np.nonzero(d <= most)
                i, j, d = x[a + i], y[b + j], d[i, j]
                keep = slice(None) if two else i < j
                edges.append(np.stack([d.astype(np.int64), i, j], axis=1)[keep])
        return ids[_spanning(np.concatenate(edges), len(ids))[:, 1:]]

    size = there.groupBy("key").agg(F.count(F.lit(1)).alias("n")).select("key", F.ceil(F.col("n") / BLOCK).cast("long").alias("blocks"))
    return links.unionByName(unit_links(block_units(there, size, ["key"]), ["key"], names[1:], compare)).distinct()


LINKS = "a long, b long, hot boolean"


def block_units(rows: DataFrame, size: DataFrame, keys: list[str]) -> DataFrame:
    """rows (keys, id, ...) with lo, hi, side: the rows of a key fall into so many blocks by a hash of the id, and every
    pair of a key's blocks (lo <= hi) is a unit that holds the rows of both. size: keys, blocks."""
    there = rows.join(size.select(*(F.col(k).alias(f"_{k}") for k in keys), "blocks"), [F.col(k) == F.col(f"_{k}") for k in keys])
    own = there.withColumn("_own", F.pmod(F.xxhash64("id", F.lit(17)), F.col("blocks"))).withColumn("_other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    return own.select(*rows.columns, F.least("_own", "_other").alias("lo"), F.greatest("_own", "_other").alias("hi"), F.col("_own").alias("side"))


def by_unit(units: DataFrame, keys: list[str], columns: list[str], settle: Callable[[tuple, list], pa.RecordBatch], schema: str) -> DataFrame:
    """Rows that settle(unit, [side, *columns]) gives, unit by unit: unit is its keys, lo and hi. A task holds one unit at a time."""
    by = [*keys, "lo", "hi"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        at = None
        for b in batches:
            place = np.stack([c.to_numpy(zero_copy_only=False) for c in b.columns[: len(by)]], axis=1)
            edges = np.r_[0, np.flatnonzero((place[1:] != place[:-1]).any(axis=1)) + 1, len(place)]
            for a, z in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                if a == z:
                    continue
                if at is not None and at != tuple(place[a]):
                    yield whole(at, held)
                    held = []
                at = tuple(place[a])
                held.append(b.slice(a, z - a))
        if held:
            yield whole(at, held)

    def whole(at: tuple, held: list[pa.RecordBatch]) -> pa.RecordBatch:
        unit = pa.Table.from_batches(held).select(["side", *columns])
        return settle(at, [c.to_numpy() if pa.types.is_integer(c.type) else c.to_pylist() for c in unit.columns])

    dealt = units.select(*by, "side", *columns).repartition(total_partitions(units.sparkSession), *by).sortWithinPartitions(*by, "side", "id")
    return dealt.mapInArrow(lean(run), schema)


def unit_links(units: DataFrame, keys: list[str], columns: list[str], compare: Callable[[list], np.ndarray]) -> DataFrame:
    """(a, b) that compare(columns side, *columns of a unit) gives, unit by unit."""
    return by_unit(units, keys, columns, lambda _, unit: link_batch(compare(unit)), LINKS).select("a", "b").distinct()


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, most: int = MAX_BITS) -> DataFrame:
    """doc_id, fingerprint, component_id for every row of docs: 64-bit fingerprints at most three bits apart are linked.

    All pairs of different fingerprints that close are met. A null text counts as empty, and texts of no words have the
    fingerprint zero, linked like any other. component_id is the least doc_id reachable (null ids are left out of the
    least, and a row with one belongs to its fingerprint's component). Repeated rows come back each.
    """
    if most > MAX_BITS:
        raise ValueError(f"the exact plan of keys covers at most {MAX_BITS} bits")
    prints = materialize_texts(fingerprints(docs, size, 1, False, id_col, text_col), "simhash-prints")
    classes = materialize(prints.groupBy("fp0").agg(F.min("doc_id").alias("least_id")), "simhash-classes")
    # a class is named by its fingerprint, and its component by the least id of all its classes
    links = materialize(bucket_links(key_rows(classes.select(F.col("fp0").alias("id"), "fp0"), "exact", 1, 1), 1, most), "simhash-links")
    roots = components(links)
    rooted = classes.join(roots, classes["fp0"] == roots["id"], "left").select("fp0", "least_id", F.coalesce("root", "fp0").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least_id").alias("component_id"))
    named = materialize(rooted.join(least, "root").select(F.col("fp0").alias("print"), "component_id"), "simhash-named")
    # plain scans under one exchange each: adaptive execution can split the partition of a hot fingerprint
    return prints.join(named, prints["fp0"] == named["print"]).select("doc_id", F.lpad(F.lower(F.hex("fp0")), 16, "0").alias("fingerprint"), "component_id")


def common_shingles(docs: DataFrame, size: int) -> np.ndarray:
    """Hashes of at most COMMON shingles that several of the looked-at texts of docs (id, text) hold, the rarest first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 64):
                sets = [np.unique(shingle_hashes(text.as_py(), size)).view(np.int64) for text in b.column(0).slice(a, 64)]
                yield pa.record_batch([pa.array(np.concatenate(sets))], names=["shingle"])

    some = docs.where(F.pmod(F.xxhash64("id"), F.lit(COMMON_ONE_IN)) == 0).select("text").mapInArrow(lean(run), "shingle long")
    with text_batches(docs.sparkSession):
        top = some.groupBy("shingle").agg(F.count(F.lit(1)).alias("n")).where("n > 1").orderBy(F.col("n").desc(), "shingle").limit(COMMON).collect()
    return np.array([r["shingle"] for r in reversed(top)], dtype=np.int64).view(np.uint64)


def prefix(hashes: np.ndarray, similarity: float, common: np.ndarray, order: np.ndarray) -> np.ndarray:
    """The first shingles of a set in the order of all: by hash, then the common ones, rarest first. Two sets with the given
    share in common have one of them in common. common: sorted; order: the place of each among the common ones."""
    if len(common) and len(hashes):
        at = np.minimum(np.searchsorted(common, hashes), len(common) - 1)
        place = np.where(common[at] == hashes, order[at] + 1, 0)
        hashes = hashes[np.lexsort((hashes, place))]
    return hashes[: len(hashes) - int(least_common(len(hashes), similarity)) + 1] if len(hashes) else hashes


def least_common(n: np.ndarray | int, similarity: float) -> np.ndarray:
    """Least shingles that a set of n shares with any set of the given similarity."""
    return np.maximum(1, np.ceil(similarity * np.asarray(n) - 1e-6).astype(np.int64))


def similar_prints(docs: DataFrame, size: int, similarity: float) -> DataFrame:
    """doc_id, fp0, ..., n, prefix (hashes as bytes) of docs (id, text): all that the search needs from a text, in one reading."""
    ranked = common_shingles(docs, size)
    order = np.argsort(ranked)
    common = docs.sparkSession.sparkContext.broadcast((ranked[order], order))
    names = ["doc_id", *(f"fp{k}" for k in range(WIDE)), "n", "prefix"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = np.zeros((b.num_rows, WIDE), dtype=np.uint64)
            sizes, firsts = [], []
            for i, text in enumerate(b.column(1)):
                h = np.unique(shingle_hashes(text.as_py(), size))
                for k in range(WIDE):
                    out[i, k] = votes(spread(h, k))
                sizes.append(len(h))
                firsts.append(prefix(h, similarity, *common.value).tobytes())
            yield pa.record_batch([b.column(0), *(pa.array(out[:, k].view(np.int64)) for k in range(WIDE)), pa.array(sizes, pa.int64()), pa.array(firsts, pa.binary())], names=names)

    return docs.mapInArrow(lean(run), ", ".join(f"{x} {'binary' if x == 'prefix' else 'long'}" for x in names))


def shared_postings(rooted: DataFrame) -> DataFrame:
    """POSTING and texts: the prefix of each text, a row a shingle, as far as texts of different roots share the shingle; texts: how many
    have it. rooted: id, root, n, prefix.

    Shingles of several roots are found before any is dealt out, and only rows whose shingle a bitmap marks go into the join.
    """

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            firsts = [np.frombuffer(x, dtype=np.int64) for x in b.column(3).to_pylist()]
            times = np.array([len(x) for x in firsts], dtype=np.int64)
            ends = np.cumsum(times)
            for lo in range(0, b.num_rows, 1024):
                hi = min(lo + 1024, b.num_rows)
                at = np.repeat(np.arange(lo, hi), times[lo:hi])
                place = np.arange(len(at)) - np.repeat(ends[lo:hi] - times[lo:hi] - (ends[lo - 1] if lo else 0), times[lo:hi])
                columns = [np.concatenate(firsts[lo:hi]), *(b.column(k).to_numpy(zero_copy_only=False)[at] for k in range(3)), place]
                yield pa.record_batch([pa.array(c) for c in columns], names=POSTING)

    return among_several(rooted.select("id", "root", "n", "prefix").mapInArrow(lean(explode), ", ".join(f"{x} long" for x in POSTING)))


POSTING = ["shingle", "id", "root", "n", "place"]


def among_several(rows: DataFrame) -> DataFrame:
    """rows (POSTING) whose shingle has several roots, with texts, the number of rows it has; written out."""
    per = rows.groupBy("shingle").agg(F.min("root").alias("_lo"), F.max("root").alias("_hi"))
    per = materialize(per.where("_lo < _hi").select(F.col("shingle").alias("_shingle")), "similar-several")
    maybe = marked(rows, bitmap_of(per, F.col("_shingle"), "similar-bitmap"), F.col("shingle"), "_maybe").where("_maybe").select(*POSTING)
    some = materialize(maybe.join(per, F.col("shingle") == F.col("_shingle"), "left_semi"), "similar-some")
    counts = some.groupBy(F.col("shingle").alias("_shingle")).agg(F.count(F.lit(1)).alias("texts"))
    out = materialize(some.join(counts, F.col("shingle") == F.col("_shingle")).select(*POSTING, "texts"), "similar-shared")
    discard(per, some)
    return out


def possible(x: np.ndarray, y: np.ndarray, similarity: float) -> np.ndarray:
    """Whether sizes and places let rows (..., id, root, n, place) that share a shingle be so similar, and of different roots. Holds at
    the first shingle in common, so nothing is lost if it fails at others."""
    n, m = x[..., 2], y[..., 2]
    left = np.minimum(n - x[..., 3], m - y[..., 3])
    need = similarity / (1 + similarity) * (n + m) - 1e-6
    return (x[..., 1] != y[..., 1]) & (np.minimum(n, m) >= similarity * np.maximum(n, m) - 1e-6) & (left >= need)


def prefix_pairs(shared: DataFrame, similarity: float, hot: int = HOT_SHINGLE) -> DataFrame:
    """(a, b), distinct: ids of different root that share a shingle of at most `hot` texts in their prefixes, as far as the number of shingles
    that the prefixes share leaves the given similarity possible.

    Prefixes hold all but the last least_common - 1 shingles in one order. Of two texts, the one whose prefix ends first has its other common
    shingles among those last ones. So common shingles are at most those of the prefixes and the more of these two rests. Shingles of more
    than `hot` texts are not counted pair by pair; a text's number of them stands for all that it may share.
    """
    often = shared.where(F.col("texts") > hot).groupBy(F.col("id").alias("_i")).agg(F.count(F.lit(1)).alias("often"))
    rows = shared.where(F.col("texts") <= hot).join(often, F.col("id") == F.col("_i"), "left").select("shingle", "id", "root", "n", F.coalesce("often", F.lit(0)).alias("often"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.empty((0, 5), np.int64)
        for b in batches:
            held = np.concatenate([held, np.stack([c.to_numpy(zero_copy_only=False) for c in b.columns], axis=1)])
            if len(held) >= 100_000:
                end = int(np.searchsorted(held[:, 0], held[-1, 0]))  # the last shingle may go on
                if end:
                    yield settle(held[:end])
                    held = held[end:]
        if len(held):
            yield settle(held)

    def settle(table: np.ndarray) -> pa.RecordBatch:
        """table: all rows of its shingles, sorted by shingle."""
        new = np.flatnonzero(np.r_[True, table[1:, 0] != table[:-1, 0]])
        size = np.diff(np.r_[new, len(table)])
        rows, found = table[:, 1:], [np.empty((0, 3), np.int64)]
        last, at = np.repeat(new + size, size), np.arange(len(table))
        for step in range(1, int(size.max())):
            at = at[at + step < last[at]]
            x, y = rows[at], rows[at + step]
            n, m = x[:, 2], y[:, 2]
            rest = np.maximum(least_common(n, similarity), least_common(m, similarity)) - 1
            need = np.ceil(similarity / (1 + similarity) * (n + m) - 1e-6).astype(np.int64) - rest - np.minimum(x[:, 3], y[:, 3])
            keep = (x[:, 1] != y[:, 1]) & (np.minimum(n, m) >= similarity * np.maximum(n, m) - 1e-6)
            found.append(np.stack([np.minimum(x[keep, 0], y[keep, 0]), np.maximum(x[keep, 0], y[keep, 0]), need[keep]], axis=1))
        pairs, times = np.unique(np.concatenate(found), axis=0, return_counts=True)
        return pa.record_batch([*(pa.array(pairs[:, k].copy()) for k in range(3)), pa.array(times)], names=["a", "b", "need", "times"])

    dealt = rows.repartition(total_partitions(shared.sparkSession), "shingle").sortWithinPartitions("shingle")
    met = dealt.mapInArrow(lean(run), "a long, b long, need long, times long").groupBy("a", "b").agg(F.min("need").alias("need"), F.sum("times").alias("times"))
    return met.where("a != b and times >= need").select("a", "b")


def sketch(hashes: np.ndarray) -> np.ndarray:
    """How many hashes of a set fall in each slot, a byte each (255: as many or more). Slots are a power of two, more than half as many as hashes."""
    slots = 1 << max(4, (len(hashes) // 2).bit_length())
    return np.minimum(np.bincount((hashes & np.uint64(slots - 1)).astype(np.int64), minlength=slots), 255).astype(np.uint8)


def folded(sketches: list[np.ndarray], slots: int) -> np.ndarray:
    """Sketches of one length, a row each, with so many slots; where a number is not known, one above all."""
    counts = np.stack(sketches).astype(np.int32)
    counts[counts == 255] = 1 << 20
    return counts.reshape(len(sketches), -1, slots).sum(axis=1)


def sketched_pairs(sketches: list[np.ndarray], sizes: np.ndarray, x: np.ndarray, y: np.ndarray, look: np.ndarray, similarity: float) -> np.ndarray:
    """look (a row for each of x, a column for each of y), without pairs whose sketches show that they are not so similar: two sets have no
    more in common than the lesser of both numbers in each slot. More slots are folded into fewer."""
    slots = np.array([len(s) for s in sketches])
    out = np.zeros_like(look)
    for p in np.unique(slots[x]).tolist():
        for q in np.unique(slots[y]).tolist():
            rows, cols = np.flatnonzero(slots[x] == p), np.flatnonzero(slots[y] == q)
            some = look[np.ix_(rows, cols)]
            rows, cols, some = rows[some.any(axis=1)], cols[some.any(axis=0)], some[some.any(axis=1)][:, some.any(axis=0)]
            if not len(rows):
                continue
            left, right = (folded([sketches[i] for i in at.tolist()], min(p, q)) for at in (x[rows], y[cols]))
            for r in range(len(rows)):
                at = np.flatnonzero(some[r])
                most = np.minimum(left[r], right[at]).sum(axis=1)
                need = similarity / (1 + similarity) * (sizes[x[rows[r]]] + sizes[y[cols[at]]]) - 1e-6
                out[rows[r], cols[at[most >= need]]] = True
    return out


def shingle_sets(named: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """(id, shingles, sketch, size): the sorted set of shingle hashes, as bytes, its sketch and its size, of each row of named (id, text) whose id
    is wanted (w); written out."""
    wanted = materialize(wanted.distinct(), "similar-wanted")
    # only texts that the bitmap of wanted ids marks are shuffled
    texts = marked(named, bitmap_of(wanted, F.xxhash64("w"), "similar-bitmap"), F.xxhash64("id"), "_maybe").where("_maybe").select("id", "text").join(wanted, F.col("id") == F.col("w"), "left_semi")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [np.unique(shingle_hashes(t.as_py(), size)) for t in b.column(1)]
            columns = [*(pa.array([f(h).tobytes() for h in found], pa.binary()) for f in (np.asarray, sketch)), pa.array([len(h) for h in found], pa.int64())]
            yield pa.record_batch([b.column(0), *columns], names=["id", "shingles", "sketch", "size"])

    return materialize_texts(texts.mapInArrow(lean(sets), "id long, shingles binary, sketch binary, size long"), "similar-shingles")


def verified(found: DataFrame, named: DataFrame, size: int, similarity: float) -> DataFrame:
    """The pairs of found (a, b) whose sets of shingles have the given share in common, written out. named: id, text."""
    hashed = shingle_sets(named, found.select(F.col("a").alias("w")).unionByName(found.select(F.col("b").alias("w"))), size)

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = []
            for x, y in zip(b.column(2), b.column(3), strict=True):
                x, y = (np.frombuffer(v.as_py(), dtype=np.uint64) for v in (x, y))
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(common > 0 and common >= similarity * (len(x) + len(y) - common))
            yield b.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep, one, two = [], np.array([0]), np.array([1])
            for x, y, n, m in zip(*(b.column(k).to_pylist() for k in (2, 4, 3, 5)), strict=True):
                both = [np.frombuffer(v, dtype=np.uint8) for v in (x, y)]
                keep.append(bool(sketched_pairs(both, np.array([n, m]), one, two, np.ones((1, 1), bool), similarity)[0, 0]))
            yield b.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    # whole sets are moved for pairs alone that their sketches leave
    side = lambda c, *what: hashed.select(F.col("id").alias(c), *(F.col(x).alias(f"{x}{c}") for x in what))
    maybe = found.join(side("a", "sketch", "size"), "a").join(side("b", "sketch", "size"), "b").select("a", "b", "sketcha", "sizea", "sketchb", "sizeb")
    maybe = materialize_texts(maybe.mapInArrow(lean(sketched), "a long, b long"), "similar-maybe")
    out = maybe.join(side("a", "shingles"), "a").join(side("b", "shingles"), "b").select("a", "b", "shinglesa", "shinglesb")
    out = materialize_texts(out.mapInArrow(lean(compare), "a long, b long"), "similar-met")
    discard(hashed, maybe)
    return out


def common_counts(sets: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """How many values each of the sets numbered x has in common with each of those numbered y: a product of 0/1 matrices over
    the values that stand in several sets, some thousand values at a time."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, value, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    several = times[value] > 1
    owner, value = owner[several], (np.cumsum(times > 1) - 1)[value[several]]
    order = np.argsort(value, kind="stable")
    owner, value = owner[order], value[order]
    out = np.zeros((len(x), len(y)), dtype=np.float32)
    for a in range(0, int(value[-1]) + 1 if len(value) else 0, 4096):
        lo, hi = np.searchsorted(value, [a, a + 4096])
        has = np.zeros((len(sets), 4096), dtype=np.float32)
        has[owner[lo:hi], value[lo:hi] - a] = 1
        out += has[x] @ has[y].T
    return out


def block_links(shared: DataFrame, named: DataFrame, size: int, similarity: float) -> DataFrame:
    """(a, b) of a verified forest in each block unit of the shingles of shared, written out. Different units may find links of the same texts.

    A text comes in as many units as it has shingles in shared, and blocks. Units first hold sketches; whole sets are moved only to units
    in which the sketches leave the text a partner.
    """
    hashed = shingle_sets(named, shared.select(F.col("id").alias("w")), size)
    per = shared.groupBy("shingle").agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("all"))
    per = per.select("shingle", F.greatest(F.ceil(F.col("k") / (BLOCK // 2)), F.ceil(F.col("all") / BLOCK_SHINGLES)).cast("long").alias("blocks"))
    units = block_units(shared.select("shingle", "id", "root", "n", "place"), per, ["shingle"])
    columns, narrow = ["id", "root", "n", "place"], ["shingle", "lo", "hi", "side", "id", "root", "n", "place"]
    beside = lambda df, what: df.join(hashed.select(F.col("id").alias("_i"), what), F.col("id") == F.col("_i"))

    def pairs(side: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        two = len(np.unique(side)) > 1
        x, y = np.flatnonzero(side == side.min()), np.flatnonzero(side == side.max())
        look = possible(rows[x][:, None], rows[y][None], similarity)
        if not two:
            look &= np.arange(len(x))[:, None] < np.arange(len(y))[None]
        return x, y, look

    def partnered(at: tuple, unit: list) -> pa.RecordBatch:
        side, rows = unit[0], np.stack(unit[1:5], axis=1)
        x, y, look = pairs(side, rows)
        if look.any():
            look = sketched_pairs([np.frombuffer(v, dtype=np.uint8) for v in unit[5]], rows[:, 2], x, y, look, similarity)
        i, j = np.nonzero(look)
        left = np.unique(np.column_stack([side, rows])[np.r_[x[i], y[j]]], axis=0)
        return pa.record_batch([*(pa.array(np.full(len(left), v, np.int64)) for v in at), *(pa.array(left[:, k].copy()) for k in range(5))], names=narrow)

    def compare(unit: list) -> np.ndarray:
        rows = np.stack(unit[1:5], axis=1)
        x, y, look = pairs(unit[0], rows)
        if not look.any():
            return np.empty((0, 2), np.int64)
        sets = [np.frombuffer(v, dtype=np.uint64) for v in unit[5]]
        i, j = np.nonzero(look)
        if len(i) <= 4 * len(sets):
            common = np.array([len(np.intersect1d(sets[x[p]], sets[y[q]], assume_unique=True)) for p, q in zip(i.tolist(), j.tolist(), strict=True)])
        else:
            common = common_counts(sets, x, y)[i, j]
        i, j = x[i], y[j]
        alike = (common > 0) & (common >= similarity * (rows[i, 2] + rows[j, 2] - common) - 1e-6)
        # texts of one root are one already
        roots, at = np.unique(rows[:, 1], return_inverse=True)
        edges = np.stack([np.zeros(int(alike.sum()), np.int64), at[i[alike]], at[j[alike]], i[alike], j[alike]], axis=1)
        forest = Forest(len(roots))
        return rows[:, 0][np.array([e[3:] for e in edges.tolist() if forest.join(e[1], e[2])], dtype=np.int64).reshape(-1, 2)]

    some = materialize_texts(by_unit(beside(units, "sketch"), ["shingle"], [*columns, "sketch"], partnered, ", ".join(f"{c} long" for c in narrow)), "similar-partnered")
    out = materialize_texts(unit_links(beside(some, "shingles"), ["shingle"], [*columns, "shingles"], compare), "similar-met")
    discard(hashed, some)
    return out


def follow(roots: DataFrame, column: str, links: DataFrame, rooted: DataFrame) -> DataFrame:
    """roots with its column of roots brought up to date by links between ids of rooted (id, root)."""
    at = lambda c: rooted.select(F.col("id").alias(c), F.col("root").alias(f"r{c}"))
    between = links.join(at("a"), "a").join(at("b"), "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    moved = components(between).select(F.col("id").alias("_was"), F.col("root").alias("_now"))
    return roots.join(moved, F.col(column) == F.col("_was"), "left").withColumn(column, F.coalesce("_now", column)).drop("_was", "_now")


def similar_links(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """(a, b) links between ids whose sets of shingles have at least the given share in common; ids are connected by links
    just when pairs of that similarity connect them.

    Keys and wide fingerprints find most links by the sampled plan, some by chance not. Then all pairs between the
    components so far whose prefixes share a shingle are compared, so none is left: those under a shingle of few texts as pairs,
    those under a frequent one in blocks, where each text first comes under one such shingle alone, so that large groups are
    together before all their shingles are gone through. Each link that is returned has been compared on the whole sets of
    shingles. Rows of null id or of no words are not linked. Rows that share an id are one document of several texts.
    """
    named = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    prints = materialize_texts(similar_prints(named, size, similarity), "similar-prints")
    fps = [f"fp{k}" for k in range(WIDE)]
    classes = materialize(prints.groupBy(*fps).agg(F.min("doc_id").alias("id"), F.count(F.lit(1)).alias("n")), "similar-classes")
    apart = bucket_links(key_rows(classes, "sampled", WIDE, 1), 1, WIDE_BITS)
    same = [F.col(f"p.{x}") == F.col(f"c.{x}") for x in fps]
    alike = prints.alias("p").join(classes.where("n > 1").alias("c"), same).where("doc_id != id").select(F.col("id").alias("a"), F.col("doc_id").alias("b"))
    found = materialize(apart.unionByName(alike), "similar-candidates")
    # of a text's candidates by one word that are alike in all words, the nearest come first, then those between what these leave apart
    side = lambda c: prints.select(F.col("doc_id").alias(c), *(F.col(x).alias(f"{x}{c}") for x in fps), F.col("n").alias(f"n{c}"))
    apart_by = sum((F.bit_count(F.col(f"{x}a").bitwiseXOR(F.col(f"{x}b"))) for x in fps), F.lit(0))
    near = found.join(side("a"), "a").join(side("b"), "b").where((apart_by <= WIDE_ALL) & (F.least("na", "nb") >= similarity * F.greatest("na", "nb") - 1e-6))
    near = materialize(near.select("a", "b", apart_by.alias("apart")).distinct(), "similar-near")
    nearest = [near.groupBy(x).agg(F.min(F.struct("apart", y)).getField(y).alias(y)).select("a", "b") for x, y in (("a", "b"), ("b", "a"))]
    links = verified(materialize(nearest[0].union(nearest[1]).distinct(), "similar-nearest"), named, size, similarity)
    at = materialize(components(links), "similar-roots")
    root_of = lambda c: at.select(F.col("id").alias(c), F.col("root").alias(f"r{c}"))
    ends = near.join(root_of("a"), "a", "left").join(root_of("b"), "b", "left").select("a", "b", "apart", F.coalesce("ra", "a").alias("ra"), F.coalesce("rb", "b").alias("rb"))
    between = ends.where("ra != rb").groupBy(F.least("ra", "rb").alias("x"), F.greatest("ra", "rb").alias("y")).agg(F.min(F.struct("apart", "a", "b")).alias("one")).select("one.a", "one.b")
    links = links.unionByName(verified(materialize(between, "similar-between"), named, size, similarity))

    roots = components(links).select(F.col("id").alias("_i"), "root")
    rooted = prints.select(F.col("doc_id").alias("id"), "n", "prefix").join(roots, F.col("id") == F.col("_i"), "left")
    shared = shared_postings(rooted.withColumn("root", F.coalesce("root", "id")))
    frequent = shared.where(F.col("texts") > HOT_SHINGLE)
    if frequent.limit(1).count():
        once = frequent.groupBy("id").agg(F.min_by("shingle", F.xxhash64("shingle")).alias("_one")).select(F.col("id").alias("_id"), "_one")
        once = materialize(frequent.join(once, (F.col("id") == F.col("_id")) & (F.col("shingle") == F.col("_one"))).select(*shared.columns), "similar-once")
        met = block_links(once, named, size, similarity)
        links = links.unionByName(met)
        shared = among_several(follow(shared.drop("texts"), "root", met, once.select("id", "root").distinct()))
        links = links.unionByName(block_links(shared.where(F.col("texts") > HOT_SHINGLE), named, size, similarity))
    rest = materialize(prefix_pairs(shared, similarity), "similar-rest")
    links = links.unionByName(verified(rest, named, size, similarity))
    discard(rest, shared, found, classes, prints)
    return links


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs without those whose component of similar texts has a lesser id, all columns as they are.

    Rows of null id, and texts of no words (null and empty ones too), are never dropped. Rows that share an id are one document of several texts and
    stay or go together. Whole texts are compared, however long. An empty table gives an empty result.
    """
    roots = components(materialize(similar_links(docs, id_col, text_col), "similar-links"))
    return without_ids(docs, materialize(roots.where("id != root").select("id"), "similar-gone"), id_col)
