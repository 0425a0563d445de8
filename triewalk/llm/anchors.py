"""Anchors of 200-byte strings: every window of a text names the least-hashed gram inside it, so equal windows name equal grams
at equal offsets wherever they stand. Runs of windows with the same anchor place are the units that repeats are looked for in."""

from __future__ import annotations

import numpy as np
import xxhash

WINDOW, GRAM = 200, 32
#: Places of the anchor in a window.
SPREAD = WINDOW - GRAM + 1
_BASE = 0x9E3779B97F4A7C15
_PLACE_BITS = 24
#: Longer texts are cut into parts that overlap by a window less one byte; a window's anchor depends on the window alone.
PART = (1 << _PLACE_BITS) - 1


def _gram_hashes(x: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of `size` bytes (a power of two), by doubling."""
    h, power, width = x.astype(np.uint64) + np.uint64(1), _BASE, 1
    while width < size:
        h = h[:-width] * np.uint64(power) + h[width:]
        power, width = power * power & (2**64 - 1), 2 * width
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    return h


def _least(h: np.ndarray, span: int) -> np.ndarray:
    """Least of each `span` values in a row."""
    width = 1
    while 2 * width <= span:
        h = np.minimum(h[:-width], h[width:])
        width *= 2
    return np.minimum(h[: len(h) - (span - width)], h[span - width :]) if span > width else h


def runs(raw: bytes) -> tuple[np.ndarray, ...]:
    """(anchor hash, slice hash, start, length, anchor's place in the slice) of each run of windows of one anchor place;
    the run's windows cover raw[start : start + length]."""
    out = []
    for base in range(0, max(1, len(raw) - WINDOW + 1), PART - WINDOW + 1):
        x = np.frombuffer(raw, dtype=np.uint8)[base : base + PART]
        if len(x) < WINDOW:
            continue
        h = _gram_hashes(x, GRAM)
        ranked = (h & ~np.uint64((1 << _PLACE_BITS) - 1)) | np.arange(len(h), dtype=np.uint64)
        least = _least(ranked, WINDOW - GRAM + 1)
        first = np.flatnonzero(np.r_[True, least[1:] != least[:-1]])
        length = np.diff(np.r_[first, len(least)]) + WINDOW - 1
        place = (least[first] & np.uint64((1 << _PLACE_BITS) - 1)).astype(np.int64)
        anchor = h[place]
        view, digest = memoryview(raw), xxhash.xxh3_64_intdigest
        content = np.array([digest(view[a : a + n]) for a, n in zip((first + base).tolist(), length.tolist(), strict=True)], dtype=np.uint64)
        out.append((anchor, content, first + base, length, place - first))
    if not out:
        return (np.empty(0, np.uint64), np.empty(0, np.uint64), *[np.empty(0, np.int64)] * 3)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


def bands(raw: bytes, place: int, width: int) -> list[tuple[int, int, int, bytes]]:
    """The windows of a slice with its anchor at place, by bands of so many places of the anchor in the window: (band, start, end,
    region) for raw[start : end], the windows in the band, and the bytes that every window of the band would hold. Equal windows
    lie in one band and under equal regions; a band of width 1 is one window, and its region the window itself."""
    least, most = max(0, place - (len(raw) - WINDOW)), min(place, SPREAD - 1)
    out = []
    for band in range(least // width, most // width + 1):
        first, last = band * width, min(band * width + width, SPREAD) - 1
        start, end = place - min(last, most), place - max(first, least) + WINDOW
        out.append((band, start, end, raw[place - first : place - last + WINDOW]))
    return out
