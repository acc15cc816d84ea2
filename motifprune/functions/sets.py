"""Set algebra on sorted arrays of vertex ids, as Spark columns; nothing here leaves the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def set_intersect(a: Column, b: Column) -> Column:
    """Keeps a's order."""
    return F.array_intersect(a, b)


def set_subtract(a: Column, b: Column) -> Column:
    return F.array_except(a, b)


def set_bound(a: Column, above: Column | None = None, below: Column | None = None) -> Column:
    """Members greater than `above` and less than `below`."""
    if above is not None:
        a = F.filter(a, lambda x: x > above)
    if below is not None:
        a = F.filter(a, lambda x: x < below)
    return a


def set_exclude(a: Column, *matched: Column) -> Column:
    return F.array_except(a, F.array(*matched)) if matched else a


def candidates_scratch(near: list[Column], far: list[Column]) -> Column:
    """All of the near lists and none of the far ones, from the whole lists."""
    out = near[0]
    for x in near[1:]:
        out = set_intersect(out, x)
    for x in far:
        out = set_subtract(out, x)
    return out
