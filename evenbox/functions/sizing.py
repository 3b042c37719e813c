"""Size arithmetic: when can a set be tiled by leaves of m..M, and where may it be cut.

Counts use whole numbers only; weights use a relative tolerance.
"""

from __future__ import annotations

import math

import numpy as np

from pyspark.sql import Column
from pyspark.sql import functions as F

TOLERANCE = 1e-9


def ceil_div(a: int, b: int) -> int:
    return -(-a // b)


def count_capacity(n: int, block: int, data: int) -> int:
    """Sample points that stand for one block."""
    return max(1, ceil_div(n * block, max(data, 1)))


def weight_capacity(total: float, parts: int, mode: str = "mean", slack: float = 0.0, block: float | None = None) -> float:
    """Largest leaf weight: the mean over ``parts`` leaves, or a block, with ``slack`` on top (no more than a block)."""
    if mode == "block":
        return float(block)
    most = math.ceil((1 + slack) * total / max(parts, 1))
    return float(min(most, block)) if block and parts > total / block else float(most)


def min_fill(most: float, alpha: float) -> int:
    """Smallest leaf size for a largest one and the wanted ratio between them."""
    return max(1, math.floor(alpha * most + TOLERANCE))


def fits(size, least, most):
    """Whether ``size`` is a sum of numbers in least..most (0 is not). Works on arrays."""
    slack = TOLERANCE * np.maximum(np.abs(size), 1)
    return (np.ceil((size - slack) / most) <= np.floor((size + slack) / least)) & (np.asarray(size) > 0)


def fits_column(size: Column, least: Column, most: Column) -> Column:
    """``fits`` on whole-number columns."""
    return (size > 0) & (F.floor((size + most - 1) / most) <= F.floor(size / least))


def always_fits_from(least: int, most: int) -> float:
    """A size from which every size fits; infinite if all leaves must be equal."""
    return math.inf if most == least else ceil_div(least, most - least) * least


def always_fits_column(least: Column, most: Column) -> Column:
    """``always_fits_from`` on whole-number columns; null where it is infinite."""
    return F.when(least < most, F.ceil(least / (most - least)) * least).cast("long")


def sample_needed(alpha: float, block: int, ratio: float, point_bytes: int) -> tuple[int, int]:
    """(points, bytes) of a sample that is sure to fit, for blocks of this size sampled at this ratio."""
    most = math.ceil(ratio * block / point_bytes)
    points = always_fits_from(min_fill(most, alpha), most)
    return points, points * point_bytes


def witness_sizes(size: int, least: int, most: int) -> list[int]:
    """Leaf sizes in least..most that add up to ``size``; empty if there are none."""
    if not fits(size, least, most):
        return []
    parts = ceil_div(size, most)
    spare, out = size - least * parts, []
    for _ in range(parts):
        more = min(spare, most - least)
        out.append(least + more)
        spare -= more
    return out


def left_ranges(total: float, least: float, most: float) -> list[tuple[float, float]]:
    """Cut positions at which what lies before can be tiled."""
    out, i = [], 1
    while i * least < total:
        out.append((i * least, i * most))
        i += 1
    return out


def right_ranges(total: float, least: float, most: float) -> list[tuple[float, float]]:
    """Cut positions at which what lies after can be tiled."""
    return [(total - b, total - a) for a, b in left_ranges(total, least, most)]


def cut_ranges(total: float, least: float, most: float) -> list[tuple[float, float]]:
    """Positions at which both sides can be tiled: merged closed ranges inside 0..total.

    From i >= least / (most - least) on, the left ranges run into each other, so only the head needs listing; the
    middle is one range when both sides are past that point.
    """
    pieces, i = [], 1
    while i * least < total:
        low, high = max(1, math.ceil((total - i * most) / most - TOLERANCE)), math.floor((total - i * least) / least + TOLERANCE)
        for j in range(low, high + 1):
            a, b = max(i * least, total - j * most), min(i * most, total - j * least)
            if a <= b and b > 0 and a < total:
                pieces.append((a, b))
        i += 1
    merged: list[tuple[float, float]] = []
    for a, b in sorted(pieces):
        if merged and a <= merged[-1][1]:
            merged[-1] = (merged[-1][0], max(merged[-1][1], b))
        else:
            merged.append((a, b))
    return merged
