"""The k-way meet of cursors by mutual skipping; a meet is a cursor itself, so meets nest."""

from __future__ import annotations

from collections import deque

import numpy as np


class SkipMeet:
    """Common keys of cursors, ascending.

    The cursors stand in a ring in the order of their keys (ties by position in the input). The first in the ring
    lags, the last leads: the first skips to the last one's key and goes to the ring's end, until first and last agree.
    """

    def __init__(self, cursors: list):
        self.ring: deque = deque()
        self.done = not cursors or any(c.done for c in cursors)
        if not self.done:
            self.ring.extend(sorted(cursors, key=lambda c: c.key))
            self._agree()

    @property
    def key(self):
        return self.ring[0].key

    def _moved(self) -> bool:
        """After the first of the ring has moved: sends it to the end, or ends the meet."""
        self.done = self.ring[0].done
        self.ring.rotate(-1)
        return not self.done

    def _agree(self) -> None:
        while not self.done and self.ring[0].key != (lead := self.ring[-1].key):
            self.ring[0].skip_to(lead)
            self._moved()

    def step(self) -> None:
        self.ring[0].step()
        if self._moved():
            self._agree()

    def skip_to(self, x) -> None:
        self.ring[0].skip_to(x)
        if self._moved():
            self._agree()


def drain(cursor) -> list:
    out = []
    while not cursor.done:
        out.append(cursor.key)
        cursor.step()
    return out


def meet_arrays(arrays: list[np.ndarray]) -> np.ndarray:
    """Meet of whole sorted distinct arrays: the smallest one is probed into the others, the next smallest first."""
    if not arrays:
        raise ValueError("a meet needs an input at least")
    keys, *rest = sorted(arrays, key=len)
    for other in rest:
        if not len(keys):
            break
        at = np.searchsorted(other, keys)
        inside = at < len(other)
        keys = keys[inside][other[at[inside]] == keys[inside]]
    return keys
