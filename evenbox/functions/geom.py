"""Box algebra on columns. A box is a list of low columns and a list of high columns, closed on all sides."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

Side = Sequence[Column]


def cols(names: Sequence[str | Column]) -> list[Column]:
    return [F.col(n) if isinstance(n, str) else n for n in names]


def product(values: Side) -> Column:
    return reduce(lambda a, b: a * b, values)


def total(values: Side) -> Column:
    return reduce(lambda a, b: a + b, values)


def every(flags: Side) -> Column:
    return reduce(lambda a, b: a & b, flags)


def volume(lo: Side, hi: Side) -> Column:
    return product([h - low for low, h in zip(lo, hi, strict=True)])


def margin(lo: Side, hi: Side) -> Column:
    return total([h - low for low, h in zip(lo, hi, strict=True)])


def overlaps(lo: Side, hi: Side, lo2: Side, hi2: Side) -> Column:
    return every([(a <= d) & (c <= b) for a, b, c, d in zip(lo, hi, lo2, hi2, strict=True)])


def contains(lo: Side, hi: Side, lo2: Side, hi2: Side) -> Column:
    """The first box holds the second."""
    return every([(a <= c) & (d <= b) for a, b, c, d in zip(lo, hi, lo2, hi2, strict=True)])


def overlap_volume(lo: Side, hi: Side, lo2: Side, hi2: Side) -> Column:
    return product([F.greatest(F.least(b, d) - F.greatest(a, c), F.lit(0)) for a, b, c, d in zip(lo, hi, lo2, hi2, strict=True)])


def union_box(lo: Side, hi: Side, lo2: Side, hi2: Side) -> tuple[list[Column], list[Column]]:
    return [F.least(a, c) for a, c in zip(lo, lo2, strict=True)], [F.greatest(b, d) for b, d in zip(hi, hi2, strict=True)]


def enlargement(lo: Side, hi: Side, lo2: Side, hi2: Side, by: str = "area") -> Column:
    """Growth of the first box's volume or margin when it takes in the second."""
    measure = volume if by == "area" else margin
    return measure(*union_box(lo, hi, lo2, hi2)) - measure(lo, hi)


def gap_squared(lo: Side, hi: Side, point: Side) -> Column:
    """Squared distance from a point to a box; 0 inside."""
    return total([F.pow(F.greatest(a - p, p - b, F.lit(0.0)), 2) for a, b, p in zip(lo, hi, point, strict=True)])


def distance_squared(a: Side, b: Side) -> Column:
    return total([(x - y) * (x - y) for x, y in zip(a, b, strict=True)])


def centre(lo: Side, hi: Side) -> list[Column]:
    return [(a + b) / 2 for a, b in zip(lo, hi, strict=True)]
