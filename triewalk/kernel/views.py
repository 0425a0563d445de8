"""Views behind the cursor interface that hold no rows: equality, constants, unions, nested joins, complements, existence."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from .meet import SkipMeet


class EqualView:
    """Pairs (x, x) as a trie cursor: any first key, and below it that key alone. The first level must be met with something finite."""

    def __init__(self, least=0):
        self.least, self.path = least, []

    @property
    def done(self) -> bool:
        return self.path[-1] is None

    @property
    def key(self):
        return self.path[-1]

    def open(self) -> None:
        self.path.append(self.path[-1] if self.path else self.least)

    def up(self) -> None:
        self.path.pop()

    def skip_to(self, x) -> None:
        if len(self.path) == 1:
            self.path[-1] = x if self.path[-1] < x else self.path[-1]
        elif self.path[-1] < x:
            self.path[-1] = None

    def step(self) -> None:
        if len(self.path) == 1:
            raise TypeError("the universe has no next key; another participant must move first")
        self.path[-1] = None


class ConstView:
    """The one key `value`."""

    def __init__(self, value):
        self.key, self.done = value, False

    def step(self) -> None:
        self.done = True

    def skip_to(self, x) -> None:
        self.done = self.done or self.key < x

    def open(self) -> None:
        self.done = False

    def up(self) -> None:
        return


class UnionView:
    """Keys of any of the cursors, ascending, each once."""

    def __init__(self, cursors: list):
        self.cursors = cursors

    def _live(self) -> list:
        return [c for c in self.cursors if not c.done]

    @property
    def done(self) -> bool:
        return not self._live()

    @property
    def key(self):
        return min(c.key for c in self._live())

    def step(self) -> None:
        least = self.key
        for c in self._live():
            if c.key == least:
                c.step()

    def skip_to(self, x) -> None:
        for c in self._live():
            if c.key < x:
                c.skip_to(x)


class JoinView:
    """A join as a trie cursor: open() goes to the next variable's meet, up() back."""

    def __init__(self, tries: list, levels: list[list[int]]):
        self.parts = [[tries[i] for i in level] for level in levels]
        self.meets: list[SkipMeet] = []

    @property
    def depth(self) -> int:
        return len(self.meets) - 1

    @property
    def done(self) -> bool:
        return self.meets[-1].done

    @property
    def key(self):
        return self.meets[-1].key

    def step(self) -> None:
        self.meets[-1].step()

    def skip_to(self, x) -> None:
        if self.key < x:
            self.meets[-1].skip_to(x)

    def open(self) -> None:
        parts = self.parts[len(self.meets)]
        for t in parts:
            t.open()
        self.meets.append(SkipMeet(parts))

    def up(self) -> None:
        self.meets.pop()
        for t in self.parts[len(self.meets)]:
            t.up()


class NotView:
    """Whether a binding is absent from a sorted relation: one skip a column."""

    def __init__(self, make_trie: Callable):
        self.make_trie = make_trie

    def __call__(self, values: tuple) -> bool:
        trie = self.make_trie()
        for v in values:
            trie.open()
            if trie.done:
                return True
            if trie.key < v:
                trie.skip_to(v)
            if trie.done or trie.key != v:
                return True
        return False


class ExistsView:
    """Visible prefixes of a join, each as soon as one witness for the hidden variables is found."""

    def __init__(self, view: JoinView, visible: int, arity: int):
        self.view, self.visible, self.arity = view, visible, arity

    def _witness(self) -> bool:
        if self.view.depth == self.arity - 1:
            return True
        self.view.open()
        found = False
        while not found and not self.view.done:
            found = self._witness()
            if not found:
                self.view.step()
        self.view.up()
        return found

    def rows(self, prefix: tuple = ()) -> Iterator[tuple]:
        self.view.open()
        while not self.view.done:
            row = (*prefix, self.view.key)
            if len(row) < self.visible:
                yield from self.rows(row)
            elif self._witness():
                yield row
            self.view.step()
        self.view.up()


class CompareView:
    """A comparison of two bound variables, tested at the first level where both are known."""

    OPS: dict[str, Callable] = {"<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "!=": lambda a, b: a != b}

    def __init__(self, op: str, left: int, right: int):
        self.test, self.left, self.right = self.OPS[op], left, right

    def __call__(self, row: tuple) -> bool:
        return self.test(row[self.left], row[self.right])
