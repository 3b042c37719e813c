"""Grow a whole layout: split from one node down until every node is a leaf.

The result is a binary tree of cuts that covers all space, so a point is routed by one comparison a level, and the
leaves' sample boxes and regions.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np

from evenbox.functions.sizing import TOLERANCE, ceil_div, fits, min_fill
from evenbox.plans.cut import Counters, Node, Spec, choose_cut


@dataclass
class Tree:
    """Cuts as arrays; a child below 0 is leaf -(child + 1). A cut is the key of the last point that goes low."""

    axis: list[int] = field(default_factory=list)
    cut: list[list[float]] = field(default_factory=list)
    lo: list[int] = field(default_factory=list)
    hi: list[int] = field(default_factory=list)

    def add(self, axis: int, cut: list[float]) -> int:
        self.axis.append(axis)
        self.cut.append(cut)
        self.lo.append(0)
        self.hi.append(0)
        return len(self.axis) - 1

    def depth(self) -> int:
        deepest, stack = 0, [(0, 1)] if self.axis else []
        while stack:
            node, level = stack.pop()
            deepest = max(deepest, level)
            stack += [(c, level + 1) for c in (self.lo[node], self.hi[node]) if c >= 0]
        return deepest

    def regions(self, d: int) -> dict[int, tuple[list[float], list[float]]]:
        """leaf -> (lows, highs); they tile space from -inf to +inf."""
        out, stack = {}, [(0 if self.axis else -1, [-np.inf] * d, [np.inf] * d)]
        while stack:
            node, low, high = stack.pop()
            if node < 0:
                out[-(node + 1)] = (low, high)
                continue
            a, c = self.axis[node], self.cut[node][0]
            stack.append((self.lo[node], low, [min(h, c) if i == a else h for i, h in enumerate(high)]))
            stack.append((self.hi[node], [max(x, c) if i == a else x for i, x in enumerate(low)], high))
        return out

    def route(self, points: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        """Leaf of every point, by the composite keys, all points a level at a time."""
        n, d = points.shape
        at = np.zeros(n, np.int64)
        if not len(self.axis):
            return at
        axis, cut, lo, hi = (np.asarray(column) for column in (self.axis, self.cut, self.lo, self.hi))
        first, columns = np.ascontiguousarray(cut[:, 0]), [np.ascontiguousarray(points[:, i]) for i in range(d)]
        live = np.arange(n)
        while len(live):
            node = at[live]
            turn, bound = axis[node], first[node]
            own = columns[0][live]
            for i in range(1, d):
                own = np.where(turn == i, columns[i][live], own)
            low = own < bound
            tied = np.flatnonzero(own == bound)
            if len(tied):  # only these need the rest of the key
                low[tied] = self._low(points, hashes, live[tied], turn[tied], cut[node[tied]])
            at[live] = np.where(low, lo[node], hi[node])
            live = live[at[live] >= 0]
        return -(at + 1)

    @staticmethod
    def _low(points: np.ndarray, hashes: np.ndarray, at: np.ndarray, axis: np.ndarray, cut: np.ndarray) -> np.ndarray:
        """Whether points go low at cuts that have their first coordinate."""
        d = points.shape[1]
        low, decided = np.ones(len(at), bool), np.zeros(len(at), bool)
        for j in range(1, d + 1):
            own = points[at, (axis + j) % d] if j < d else hashes[at]
            less, more = own < cut[:, j], own > cut[:, j]
            low[more & ~decided] = False
            decided |= less | more
        return low


@dataclass
class Layout:
    method: str
    tree: Tree
    boxes: dict[int, tuple[list[float], list[float]]]
    weights: dict[int, float]
    counts: dict[int, int]
    counters: Counters
    spec: Spec | None = None

    @property
    def parts(self) -> int:
        return len(self.boxes)

    def extent(self, d: int) -> tuple[list[float], list[float]]:
        """The box of the sample the layout was learned from."""
        ends = [b for b in self.boxes.values() if len(b[0]) == d]
        return ([min((b[0][i] for b in ends), default=0.0) for i in range(d)], [max((b[1][i] for b in ends), default=1.0) for i in range(d)])


def scale(points: np.ndarray) -> np.ndarray:
    """Coordinates in units of each axis' extent, so margins of different units can be added."""
    low, high = points.min(axis=0), points.max(axis=0)
    return (points - low) / np.where(high > low, high - low, 1)


def repaired(size: float, spec: Spec) -> Spec:
    """A spec the root can be tiled under: the smallest leaf is lowered if need be."""
    if not spec.balanced or fits(size, spec.least, spec.most):
        return spec
    parts = max(1, int(np.ceil(size / spec.most - TOLERANCE)))
    return replace(spec, least=max(1 if spec.variant == "count" else TOLERANCE, size // parts if spec.variant == "count" else size / parts))


def grow(points: np.ndarray, hashes: np.ndarray, spec: Spec, weights: np.ndarray | None = None, normalise: bool = True, method: str | None = None) -> Layout:
    """Split all sample points down to leaves of ``spec.least``..``spec.most``."""
    n = len(points)
    weights = np.ones(n) if weights is None or spec.variant != "bytes" else np.asarray(weights, float)
    counters, tree = Counters(), Tree()
    spec = repaired(float(weights.sum()) if spec.variant == "bytes" else n, spec)
    root = Node(np.arange(n), scale(points) if normalise and n else points, points, hashes, weights)
    boxes, totals, counts = {}, {}, {}
    stack: list[tuple[Node, int, str]] = [(root, -1, "")]
    while stack:
        node, parent, side = stack.pop()
        size = node.total() if spec.variant == "bytes" else len(node)
        full = size > spec.most * (1 + TOLERANCE)
        found = choose_cut(node, spec, counters) if full else None
        if found is None:
            counters.oversize += full
            leaf = len(boxes)
            own = points[node.at]
            boxes[leaf] = (own.min(axis=0).tolist(), own.max(axis=0).tolist()) if len(node) else ([0.0], [0.0])
            totals[leaf], counts[leaf] = node.total(), len(node)
            child = -(leaf + 1)
        else:
            axis, order, k, moved = found
            last, nxt = node.at[order[k - 1]], node.at[order[k]]
            counters.tied += bool(points[last, axis] == points[nxt, axis])
            d = points.shape[1]
            key = [*[float(points[last, (axis + j) % d]) for j in range(d)], float(hashes[last])]
            child = tree.add(axis, key)
            low, high = node.halves(order, k, moved)
            stack += [(high, child, "hi"), (low, child, "lo")]
        if parent >= 0:
            getattr(tree, side)[parent] = child
    return Layout(method or f"mbs_{spec.variant}", tree, boxes, totals, counts, counters, spec)


def default_headroom(n: int, data: int, block: int) -> float:
    """1.5 / sqrt(points of a leaf), .15 at most."""
    return min(0.15, 1.5 / np.sqrt(max(1, ceil_div(n * block, max(data, 1)))))


def plan_spec(variant: str, n: int, data: int, block: int, total: float | None = None, alpha: float = 0.95, rho: float = 0.4, headroom: float | None = 0.0, capacity: str = "block", cost: str = "area") -> Spec:
    """Capacities of a layout: n sample points stand for ``data`` bytes in blocks of ``block`` bytes.

    headroom lowers the largest size so that sampling noise seldom passes a block; None takes the default.
    """
    count = max(1, ceil_div(n * block, max(data, 1)))
    if headroom is None:
        headroom = default_headroom(n, data, block)
    if variant == "bytes":
        total = float(data if total is None else total)
        parts = ceil_div(data, block)
        most = float(block) if capacity == "block" else float(np.ceil(total / max(parts, 1)))
        most *= 1 - headroom
        return Spec("bytes", alpha * most, most, rho, cost)
    most = max(1, int(count * (1 - headroom)))
    return Spec(variant, min_fill(most, 0.3 if variant == "plain" else alpha), most, rho, cost)


def grow_top(points: np.ndarray, hashes: np.ndarray, spec: Spec, weights: np.ndarray | None, most: float) -> Layout:
    """The first levels only: nodes of at most ``most`` become subtrees to finish elsewhere."""
    n = len(points)
    weights = np.ones(n) if weights is None or spec.variant != "bytes" else weights
    spec = repaired(float(weights.sum()) if spec.variant == "bytes" else n, spec)
    counters, tree = Counters(), Tree()
    stack, boxes, totals, counts = [(Node(np.arange(n), scale(points), points, hashes, weights), -1, "")], {}, {}, {}
    while stack:
        node, parent, side = stack.pop()
        size = node.total() if spec.variant == "bytes" else len(node)
        found = choose_cut(node, spec, counters) if size > most else None
        if found is None:
            leaf = len(boxes)
            boxes[leaf], totals[leaf], counts[leaf] = node.at, node.total(), len(node)
            child = -(leaf + 1)
        else:
            axis, order, k, moved = found
            d, last = points.shape[1], node.at[order[k - 1]]
            child = tree.add(axis, [*[float(points[last, (axis + j) % d]) for j in range(d)], float(hashes[last])])
            low, high = node.halves(order, k, moved)
            stack += [(high, child, "hi"), (low, child, "lo")]
        if parent >= 0:
            getattr(tree, side)[parent] = child
    return Layout("top", tree, boxes, totals, counts, counters, spec)
