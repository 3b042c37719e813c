"""One split of a set of sample points.

Points are ordered along an axis by a composite key: the coordinates from that axis on, around, then a
hash of the record, so no two points tie and every place in the order is a legal cut. Running boxes from
both ends give the cost of all cuts at once.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np

from evenbox.functions.sizing import TOLERANCE, cut_ranges, fits


@dataclass(frozen=True)
class Spec:
    """What to grow. variant: plain, count or bytes; cost: area, overlap or margin."""

    variant: str = "bytes"
    least: float = 1.0
    most: float = 1.0
    rho: float = 0.4
    cost: str = "area"

    @property
    def balanced(self) -> bool:
        return self.variant != "plain"


@dataclass
class Counters:
    relaxed: int = 0
    corrected: int = 0
    tied: int = 0
    other_axis: int = 0
    unbalanced: int = 0
    oversize: int = 0


@dataclass
class Node:
    """Points of a node: rows in the sample, coordinates scaled (for costs) and raw (for order), hashes, weights."""

    at: np.ndarray
    points: np.ndarray
    raw: np.ndarray
    hashes: np.ndarray
    weights: np.ndarray
    #: the order along every axis; sorted where a node begins, handed down to its halves
    orders: list[np.ndarray] | None = None

    def __len__(self) -> int:
        return len(self.at)

    def total(self) -> float:
        return float(self.weights.sum())

    def take(self, index: np.ndarray, weights: np.ndarray) -> Node:
        return Node(self.at[index], self.points[index], self.raw[index], self.hashes[index], weights)

    def order(self, axis: int) -> np.ndarray:
        if self.orders is None:
            self.orders = [axis_order(self.raw, self.hashes, a) for a in range(self.raw.shape[1])]
        return self.orders[axis]

    def halves(self, order: np.ndarray, k: int, weights: np.ndarray) -> tuple[Node, Node]:
        """The first k points of an order and the rest, with their orders along every axis, which need no sorting again."""
        low, high = self.take(order[:k], weights[:k]), self.take(order[k:], weights[k:])
        if self.orders is not None:
            place = np.empty(len(order), np.int64)
            place[order] = np.arange(len(order))
            low.orders, high.orders = [], []
            for held in self.orders:
                moved = place[held]
                first = moved < k
                low.orders.append(moved[first])
                high.orders.append(moved[~first] - k)
        return low, high


def axis_order(points: np.ndarray, hashes: np.ndarray, axis: int) -> np.ndarray:
    d = points.shape[1]
    keys = [hashes, *[points[:, (axis + j) % d] for j in reversed(range(d))]]
    return np.lexsort(keys)


@dataclass
class Sweep:
    """Costs of the cuts after 1..n-1 points of an order."""

    order: np.ndarray
    area: np.ndarray
    margin: np.ndarray
    overlap: np.ndarray
    edges: np.ndarray = field(repr=False, default=None)


def sweep(points: np.ndarray, order: np.ndarray) -> Sweep:
    p = points[order]
    low, high = np.minimum.accumulate(p), np.maximum.accumulate(p)
    low_r, high_r = np.minimum.accumulate(p[::-1])[::-1], np.maximum.accumulate(p[::-1])[::-1]
    left, right = (high - low)[:-1], (high_r - low_r)[1:]
    both = np.minimum(high[:-1], high_r[1:]) - np.maximum(low[:-1], low_r[1:])
    return Sweep(order, left.prod(axis=1) + right.prod(axis=1), left.sum(axis=1) + right.sum(axis=1), np.maximum(both, 0).prod(axis=1))


def margins(points: np.ndarray, order: np.ndarray, first: int, last: int) -> np.ndarray:
    """``sweep``'s margins of the cuts after first..last points only."""
    p = points[order].T.copy()
    inner, n = p[:, first:last], p.shape[1]
    out = np.zeros(last - first + 1)
    for steps, outer in ((inner, p[:, :first]), (inner[:, ::-1], p[:, last:n])):
        ends = []
        for f in (np.minimum, np.maximum):
            begun = np.concatenate([f.reduce(outer, axis=1)[:, None], steps], axis=1)
            ends.append(f.accumulate(begun, axis=1, out=begun))
        total = (ends[1] - ends[0]).T.copy().sum(axis=1)  # added up as in sweep, to the last bit
        out += total if steps is inner else total[::-1]
    return out


def window(n: int, least: float, rho: float) -> tuple[int, int]:
    """First and last cut that leave the wanted fraction on either side."""
    low = max(1, math.ceil(max(least, rho * n) - TOLERANCE))
    low = min(low, max(n // 2, 1))
    return low, n - low


def allowed(node: Node, order: np.ndarray, spec: Spec) -> np.ndarray:
    """Flags of the cuts whose sides can both be tiled, by count or by weight."""
    n = len(node)
    k = np.arange(1, n)
    if not spec.balanced:
        return np.ones(n - 1, bool)
    if spec.variant == "count":
        return fits(k, spec.least, spec.most) & fits(n - k, spec.least, spec.most)
    position = np.cumsum(node.weights[order])[:-1]
    total = node.total()
    ok = fits(position, spec.least, spec.most) & fits(total - position, spec.least, spec.most)
    # each side also needs a point for each leaf
    enough = (k >= np.ceil(position / spec.most - TOLERANCE)) & (n - k >= np.ceil((total - position) / spec.most - TOLERANCE))
    return np.where((ok & enough).any(), ok & enough, ok)


def correct_weights(weights: np.ndarray, ranges: list[tuple[float, float]]) -> tuple[np.ndarray, int]:
    """Move one point's position into the middle of every range that holds none.

    The point moved is the first after the range; it gets lighter and its successor heavier by as much, so all other
    positions stay. At the end of the order the point before the range moves up at the cost of its successor.
    Returns the weights and the ranges that got a point.
    """
    position, moved, n = np.cumsum(weights).astype(float), 0, len(weights)
    total = position[-1]
    for a, b in ranges:
        middle = (a + b) / 2
        after = int(np.searchsorted(position, b, "right"))
        slack = TOLERANCE * total
        if ((position[: n - 1] >= a - slack) & (position[: n - 1] <= b + slack)).any():
            continue
        before = position[after - 1] if after else 0.0
        if after < n - 1 and before < middle < position[after]:
            position[after] = middle
        elif 0 < after and after - 1 < n - 1 and (position[after - 2] if after > 1 else 0.0) < middle < position[after]:
            position[after - 1] = middle
        else:
            continue
        moved += 1
    return np.diff(position, prepend=0.0), moved


def least_cost(costs: Sweep, ok: np.ndarray, kind: str) -> int:
    """The allowed cut (points on the left) of least cost; ties by the other costs, balance, place."""
    at = np.flatnonzero(ok)
    n = len(ok) + 1
    main = {"area": (costs.overlap, costs.area, costs.margin), "overlap": (costs.overlap, costs.area, costs.margin), "margin": (costs.margin, costs.area, costs.overlap)}[kind]
    if kind == "area":
        main = (costs.area, costs.margin, costs.overlap)
    keys = [at, np.abs(at + 1 - n / 2), *[m[at] for m in reversed(main)]]
    return int(at[np.lexsort(keys)[0]]) + 1


def choose_cut(node: Node, spec: Spec, counters: Counters) -> tuple[int, np.ndarray, int, np.ndarray] | None:
    """(axis, order, k, weights in that order), or None if the node cannot be cut."""
    n, d = node.points.shape
    if n < 2:
        return None
    low, high = window(n, spec.least if not spec.balanced else 1, spec.rho)
    inside = np.zeros(n - 1, bool)
    inside[low - 1 : high] = True
    axes = sorted(range(d), key=lambda a: (float(margins(node.points, node.order(a), low, high).sum()), a))
    for turn, axis in enumerate(axes):
        costs = sweep(node.points, node.order(axis))
        weights = node.weights[costs.order]
        ok = allowed(node, costs.order, spec)
        found = ok & inside
        if not found.any() and ok.any():
            counters.relaxed += 1
            found = ok
        if not found.any() and spec.variant == "bytes":
            changed, moved = correct_weights(weights, cut_ranges(node.total(), spec.least, spec.most))
            if moved:
                counters.corrected += 1
                trial = node.take(costs.order, changed)
                ok = allowed(trial, np.arange(n), spec)
                found = ok & inside if (ok & inside).any() else ok
                weights = changed if found.any() else weights
        if found.any():
            counters.other_axis += turn > 0
            return axis, costs.order, least_cost(costs, found, spec.cost), weights
    counters.unbalanced += 1
    axis = axes[0]
    costs = sweep(node.points, node.order(axis))
    return axis, costs.order, least_cost(costs, inside, spec.cost), node.weights[costs.order]
