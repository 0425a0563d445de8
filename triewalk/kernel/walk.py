"""The n-ary join inside a task: a scalar depth-first walk, which counts every move, and a block walk on arrays."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .cursor import OpCounter
from .meet import SkipMeet
from .trie import TrieCursor


def walk(tries: list[TrieCursor], levels: list[list[int]]) -> Iterator[tuple]:
    """Bindings of all variables in ascending order. levels[i]: which tries hold variable i; each trie's columns follow the order."""

    def below(depth: int, bound: tuple) -> Iterator[tuple]:
        parts = [tries[i] for i in levels[depth]]
        for t in parts:
            t.open()
        meet = SkipMeet(parts)
        while not meet.done:
            row = (*bound, meet.key)
            if depth + 1 == len(levels):
                yield row
            else:
                yield from below(depth + 1, row)
            meet.step()
        for t in parts:
            t.up()

    return below(0, ())


def count_moves(atoms: list[tuple[list[int], list[tuple]]], k: int) -> tuple[list[tuple], OpCounter]:
    """Answer and moves of the scalar walk. atoms: (positions of its variables in the order, rows)."""
    ops = OpCounter()
    tries = [TrieCursor.of(rows, len(at), ops=ops, name=str(i), depth_levels=at) for i, (at, rows) in enumerate(atoms)]
    return list(walk(tries, [[i for i, (at, _) in enumerate(atoms) if v in at] for v in range(k)])), ops


class ColumnTrie:
    """Sorted distinct rows as columns, with where the runs of equal prefixes begin at each depth."""

    def __init__(self, columns: list[np.ndarray]):
        self.columns, self.n = columns, len(columns[0])
        self.starts: list[np.ndarray] = []  # first rows of the runs of each depth
        self.run: list[np.ndarray] = []  # number of each row's run
        new = np.zeros(self.n, dtype=bool)
        if self.n:
            new[0] = True
        for c in columns:
            new = new | np.r_[new[:1], c[1:] != c[:-1]] if self.n else new
            self.starts.append(np.r_[np.flatnonzero(new), self.n])
            self.run.append(np.cumsum(new) - 1)

    @classmethod
    def of(cls, columns: list[np.ndarray]) -> ColumnTrie:
        """Sorts and removes repeats; pairs whose spans multiply within 63 bits as one number."""
        if len(columns) == 2 and len(columns[0]) and all(c.dtype == np.int64 for c in columns):
            (a, b), (y, z) = (int(c.min()) for c in columns), (int(c.max()) for c in columns)
            width = z - b + 1
            if (y - a + 1) * width < 1 << 63:
                key = np.sort((columns[0] - a) * width + (columns[1] - b))
                first, second = np.divmod(key[np.r_[True, key[1:] != key[:-1]]], width)
                return cls([first + a, second + b])
        order = np.lexsort(columns[::-1])
        columns = [c[order] for c in columns]
        if len(order):
            new = np.r_[True, np.any([c[1:] != c[:-1] for c in columns], axis=0)]
            columns = [c[new] for c in columns]
        return cls(columns)

    def children(self, depth: int, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """How many different values stand at a depth in each range of rows (not empty, of one parent)."""
        return self.run[depth][hi - 1] - self.run[depth][lo] + 1

    def holds(self, depth: int, lo: np.ndarray, hi: np.ndarray, value: np.ndarray) -> np.ndarray:
        """Whether each range holds its value. With small values at the second of two columns a table of bits answers at once."""
        if depth == 1 and len(self.columns) == 2:
            table = self._bits()
            if table is not None:
                bits, least, width = table
                at = value - least
                inside = (at >= 0) & (at < width)
                place = self.run[0][lo] * width + np.where(inside, at, 0)
                return inside & ((bits[place >> 3] >> (place & 7).astype(np.uint8)) & 1).astype(bool)
        return self.find(depth, lo, hi, value)[0]

    def _bits(self) -> tuple[np.ndarray, int, int] | None:
        """(bits, least value, width): for each first value and each place from the least second value a bit; None if that takes over
        eight times as many bytes as the rows."""
        if not hasattr(self, "_table"):
            least = int(self.columns[1].min())
            width = int(self.columns[1].max()) - least + 1
            first = len(self.starts[0]) - 1
            if first * width > 1024 * self.n or width > 1 << 40:
                self._table = None
            else:
                bits = np.zeros(-(-first * width // 8), dtype=np.uint8)
                place = self.run[0] * width + (self.columns[1] - least)
                np.bitwise_or.at(bits, place >> 3, (1 << (place & 7)).astype(np.uint8))
                self._table = (bits, least, width)
        return self._table

    def find(self, depth: int, lo: np.ndarray, hi: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(found, lo, hi): the run of each value in its range, all ranges halved at once."""
        column, a, z = self.columns[depth], lo.copy(), hi.copy()
        while (open_ := a < z).any():
            mid = (a + z) // 2
            less = np.zeros(len(a), dtype=bool)
            less[open_] = column[mid[open_]] < value[open_]
            a = np.where(open_ & less, mid + 1, a)
            z = np.where(open_ & ~less, mid, z)
        found = a < hi
        found[found] = column[a[found]] == value[found]
        end = np.full(len(a), 0, dtype=np.int64)
        end[found] = self.starts[depth][self.run[depth][a[found]] + 1]
        return found, a, end


class BitRows:
    """Second values of pairs as rows of bits over numbered names, each row from its first byte that holds one to its last."""

    def __init__(self, trie: ColumnTrie, names: np.ndarray):
        place = np.searchsorted(names, trie.columns[1])
        byte, edge = place >> 3, trie.starts[0]
        self.first = byte[edge[:-1]]
        self.past = byte[edge[1:] - 1] + 1
        width = self.past - self.first
        self.shift = np.cumsum(width) - width - self.first  # from a byte's number to its place in bits
        at = self.shift[trie.run[0]] + byte
        new = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        self.bits = np.zeros(int(width.sum()), dtype=np.uint8)
        self.bits[at[new]] = np.bitwise_or.reduceat((1 << (place & 7)).astype(np.uint8), new)


def bit_rows(tries: list[ColumnTrie], parts: list[tuple[int, int]]) -> tuple[np.ndarray, BitRows, BitRows] | None:
    """(names, rows of each) if a variable is the second of just two tries of pairs and the rows take no more room than the pairs."""
    if len(parts) != 2 or any(d != 1 or len(tries[t].columns) != 2 for t, d in parts):
        return None
    names = np.unique(np.concatenate([tries[t].columns[1] for t, _ in parts]))
    for t, _ in parts:
        edge, second = tries[t].starts[0], tries[t].columns[1]
        spans = np.searchsorted(names, second[edge[1:] - 1]) - np.searchsorted(names, second[edge[:-1]])
        if (spans // 8 + 2).sum() > 16 * tries[t].n:
            return None
    return names, *(BitRows(tries[t], names) for t, _ in parts)


def count_answers(tries: list[ColumnTrie], levels: list[list[tuple[int, int]]], batch_rows: int = 1 << 16) -> int:
    """How many bindings there are, none of them listed: the last variable's values are counted where they are found."""
    total = np.zeros(1, dtype=np.int64)
    for _ in walk_batches(tries, levels, batch_rows, total=total):
        raise AssertionError("a count lists nothing")
    return int(total[0])


def walk_batches(tries: list[ColumnTrie], levels: list[list[tuple[int, int]]], batch_rows: int = 1 << 16, costs: np.ndarray | None = None, total: np.ndarray | None = None, lists: bool = False) -> Iterator[list[np.ndarray]]:
    """Bindings as blocks of columns. levels[i]: (trie, depth in it) of each participant of variable i.

    A block of prefixes keeps a range of rows a trie. Of a prefix's participants the one with the fewest children is
    expanded and the others are searched; blocks are cut to batch_rows and done depth first, so memory does not grow
    with the answer. costs[i], if given, gathers the rows expanded at level i, which is its level cost. total, if given,
    gathers the number of bindings, and none is yielded. lists: a block is a row a prefix without the last variable, then how many values
    each prefix has, then all the values; two slices that lie dense are met as rows of bits.
    """
    if any(t.n == 0 for t in tries):
        return
    dense = bit_rows(tries, levels[-1]) if lists else None

    def go(level: int, prefix: list[np.ndarray], ranges: list[tuple[np.ndarray, np.ndarray]]) -> Iterator[list[np.ndarray]]:
        parts = levels[level]
        n = len(ranges[0][0])
        kids = np.stack([tries[t].children(d, *ranges[t]) for t, d in parts])
        least = kids.argmin(axis=0)
        amount = kids.min(axis=0)
        if total is not None and costs is None and len(parts) == 1 and level + 1 == len(levels):
            total[0] += amount.sum()  # every value of the one slice is an answer
            return
        if dense and level + 1 == len(levels):
            (t, _), (u, _) = parts
            x, y = (tries[w].run[0][ranges[w][0]] for w in (t, u))
            _, one, other = dense
            begins = np.maximum(one.first[x], other.first[y])
            bytes_ = np.maximum(np.minimum(one.past[x], other.past[y]) - begins, 0)
            near = bytes_ <= 2 * amount  # else the fewer values are searched one at a time
            yield from meet_bits(prefix, x, y, begins, bytes_, np.flatnonzero(near & (bytes_ > 0)))
            rest = np.flatnonzero(~near)
            prefix, ranges, least, amount, n = [p[rest] for p in prefix], [(lo[rest], hi[rest]) for lo, hi in ranges], least[rest], amount[rest], len(rest)
        begin = 0
        # cut so that each piece expands to about batch_rows
        upto = np.cumsum(amount)
        while begin < n:
            past = int(np.searchsorted(upto, (upto[begin - 1] if begin else 0) + batch_rows, side="right"))
            end = max(begin + 1, past)
            yield from piece(level, prefix, ranges, least, amount, slice(begin, end))
            begin = end

    def meet_bits(prefix: list, x: np.ndarray, y: np.ndarray, begins: np.ndarray, bytes_: np.ndarray, rows: np.ndarray) -> Iterator[list[np.ndarray]]:
        names, one, other = dense
        upto, begin = np.cumsum(bytes_[rows]), 0
        while begin < len(rows):
            end = max(begin + 1, int(np.searchsorted(upto, (upto[begin - 1] if begin else 0) + batch_rows // 4, side="right")))
            at = rows[begin:end]
            width = bytes_[at]
            past = np.cumsum(width)
            byte = np.arange(past[-1]) + np.repeat(begins[at] - past + width, width)
            both = one.bits[byte + np.repeat(one.shift[x[at]], width)] & other.bits[byte + np.repeat(other.shift[y[at]], width)]
            bit = np.flatnonzero(np.unpackbits(both, bitorder="little").view(bool))
            if len(bit):
                n = np.diff(np.searchsorted(bit, past * 8), prepend=0)
                yield [*(p[at] for p in prefix), n, names[(byte[bit >> 3] << 3) + (bit & 7)]]
            begin = end

    def piece(level: int, prefix: list, ranges: list, least: np.ndarray, amount: np.ndarray, part: slice) -> Iterator[list[np.ndarray]]:
        for k, (t, d) in enumerate(levels[level]):
            rows = np.flatnonzero(least[part] == k) + part.start
            if not len(rows):
                continue
            trie, width = tries[t], amount[rows]
            of = np.repeat(rows, width)
            nth = np.arange(len(of)) - np.repeat(np.cumsum(width) - width, width)
            run = trie.run[d][ranges[t][0][of]] + nth
            lo, hi = trie.starts[d][run], trie.starts[d][run + 1]
            value = trie.columns[d][lo]
            if costs is not None:
                costs[level] += len(of)
            now = {t: (lo, hi)}
            keep = np.ones(len(of), dtype=bool)
            counting = total is not None and level + 1 == len(levels)
            for u, e in levels[level]:
                if u == t:
                    continue
                at = of[keep]
                if counting:
                    keep[np.flatnonzero(keep)[~tries[u].holds(e, ranges[u][0][at], ranges[u][1][at], value[keep])]] = False
                    continue
                found, a, z = tries[u].find(e, ranges[u][0][at], ranges[u][1][at], value[keep])
                for w in now:
                    now[w] = tuple(x[found] for x in now[w])
                now[u] = (a[found], z[found])
                keep[np.flatnonzero(keep)[~found]] = False
            if counting:
                total[0] += int(keep.sum())
                continue
            of, value = of[keep], value[keep]
            if not len(of):
                continue
            if lists and level + 1 == len(levels):
                new = np.flatnonzero(np.r_[True, of[1:] != of[:-1]])
                yield [*(p[of[new]] for p in prefix), np.diff(new, append=len(of)), value]
                continue
            columns = [*(p[of] for p in prefix), value]
            if level + 1 == len(levels):
                yield columns
            else:
                yield from go(level + 1, columns, [now.get(u, (r[0][of], r[1][of])) for u, r in enumerate(ranges)])

    one = [(np.zeros(1, dtype=np.int64), np.full(1, t.n, dtype=np.int64)) for t in tries]
    yield from go(0, [], one)
