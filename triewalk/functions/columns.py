"""Column helpers by group: text, dates, numbers, hashes, arrays, maps, JSON, conditions, bits."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def log2(x: Column) -> Column:
    return F.log2(x)


def first_word(text: Column) -> Column:
    return F.lower(F.regexp_extract(text, r"([^\s]+)", 1))


def words_in(text: Column) -> Column:
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != ""))


def days_between(a: Column, b: Column) -> Column:
    return F.datediff(a, b)


def month_start(ts: Column) -> Column:
    return F.date_trunc("month", ts)


def power_floor(x: Column, root: int) -> Column:
    """Whole part of the root-th root."""
    return F.floor(F.pow(x, F.lit(1.0 / root)) + F.lit(1e-9)).cast("long")


def cell_of(key: Column, share: int) -> Column:
    """Number of the cell along one variable."""
    return F.pmod(F.xxhash64(key.cast("long")), F.lit(share)).cast("int")


def meet_lists(*lists: Column) -> Column:
    """Common values of sorted lists, sorted: the array form of a meet, for small slices."""
    return F.array_sort(reduce(F.array_intersect, lists))


def slices_map(keys: Column, lists: Column) -> Column:
    return F.map_from_arrays(keys, lists)


def json_long(text: Column, path: str) -> Column:
    return F.get_json_object(text, path).cast("long")


def tag_mask(tag: Column) -> Column:
    """Mask of one bit by tag number."""
    return F.pow(F.lit(2), tag).cast("long")


def masks_full(mask: Column, k: int) -> Column:
    return F.bit_count(mask) == k


def bracket(x: Column, cuts: list[float], names: list[str]) -> Column:
    out = F.lit(names[-1])
    for c, n in reversed(list(zip(cuts, names[:-1], strict=True))):
        out = F.when(x < c, F.lit(n)).otherwise(out)
    return F.coalesce(out, F.lit(names[-1]))
