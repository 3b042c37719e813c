"""Baseline layouts from a sample: slab packing, medians, quadrants, uniform grid, curve runs.

Slabs, medians, quadrants and grids give regions, so they share the tree and its router. Curves give cut
points on a one-dimensional key.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from evenbox.functions.curves import curve_bits, hilbert_key_np, z_key_np
from evenbox.plans.cut import Counters, axis_order
from evenbox.plans.grow import Layout, Tree


def fan_out(parts: int, d: int) -> int:
    """Slabs for each axis: the least f with f^d cells or more."""
    f = max(1, int(parts ** (1 / d)))
    while f**d < parts:
        f += 1
    while f > 1 and (f - 1) ** d >= parts:
        f -= 1
    return f


def _key(points: np.ndarray, hashes: np.ndarray, at: int, axis: int) -> list[float]:
    d = points.shape[1]
    return [*[float(points[at, (axis + j) % d]) for j in range(d)], float(hashes[at])]


def _binary(tree: Tree, axis: int, cuts: list[list[float]], children: list[int]) -> int:
    """A balanced chain of cuts on one axis over the children in order."""
    if len(children) == 1:
        return children[0]
    middle = len(children) // 2
    node = tree.add(axis, cuts[middle - 1])
    tree.lo[node] = _binary(tree, axis, cuts[: middle - 1], children[:middle])
    tree.hi[node] = _binary(tree, axis, cuts[middle:], children[middle:])
    return node


def _layout(method: str, points: np.ndarray, tree: Tree, leaves: list[np.ndarray]) -> Layout:
    boxes = {i: (points[at].min(axis=0).tolist(), points[at].max(axis=0).tolist()) if len(at) else ([], []) for i, at in enumerate(leaves)}
    counts = {i: len(at) for i, at in enumerate(leaves)}
    return Layout(method, _rooted(tree), boxes, {i: float(n) for i, n in counts.items()}, counts, Counters())


def _rooted(tree: Tree) -> Tree:
    """The same tree with its root at 0: nodes are renumbered from the one that is nobody's child."""
    if not tree.axis:
        return tree
    inner = {c for c in [*tree.lo, *tree.hi] if c >= 0}
    root = next(i for i in range(len(tree.axis)) if i not in inner)
    order, stack = [], [root]
    while stack:
        node = stack.pop()
        order.append(node)
        stack += [c for c in (tree.hi[node], tree.lo[node]) if c >= 0]
    place = {node: i for i, node in enumerate(order)}
    move = lambda c: place[c] if c >= 0 else c
    return Tree([tree.axis[i] for i in order], [tree.cut[i] for i in order], [move(tree.lo[i]) for i in order], [move(tree.hi[i]) for i in order])


def slab_edges(n: int, f: int) -> list[int]:
    """Where f slabs of n points begin, and n."""
    small, more = divmod(n, f)
    return [small * i + min(i, more) for i in range(f + 1)]


def slabs(points: np.ndarray, hashes: np.ndarray, parts: int, level: int = 0) -> Layout:
    """Sort-tile: f equal-count slabs on the first axis, each cut alike on the next, and so on. ``level``: axes that are cut already."""
    d, tree, leaves = points.shape[1], Tree(), []
    f = fan_out(parts, d)

    def build(at: np.ndarray, axis: int) -> int:
        if axis == d:
            leaves.append(at)
            return -len(leaves)
        order = at[axis_order(points[at], hashes[at], axis)]
        edges = slab_edges(len(order), f)
        pieces = [order[a:b] for a, b in zip(edges, edges[1:], strict=False) if b > a]
        return _binary(tree, axis, [_key(points, hashes, p[-1], axis) for p in pieces[:-1]], [build(p, axis + 1) for p in pieces])

    build(np.arange(len(points)), level)
    return _layout("str", points, tree, leaves)


def runs(points: np.ndarray, hashes: np.ndarray, parts: int) -> Layout:
    """Equal-count ranges of the first axis."""
    order = axis_order(points, hashes, 0)
    pieces, tree = [p for p in np.array_split(order, max(1, parts)) if len(p)], Tree()
    _binary(tree, 0, [_key(points, hashes, p[-1], 0) for p in pieces[:-1]], [-(i + 1) for i in range(len(pieces))] or [-1])
    return _layout("range", points, tree, pieces)


def _parted(points: np.ndarray, hashes: np.ndarray, at: np.ndarray, axis: int, k: int) -> tuple[np.ndarray, int, np.ndarray]:
    """The first k points in the order of an axis, the last of them, and the others; only those that tie with it are sorted."""
    own = points[at, axis]
    bound = np.partition(own, k - 1)[k - 1]
    less, tied = at[own < bound], at[own == bound]
    tied = tied[axis_order(points[tied], hashes[tied], axis)]
    more = k - len(less)
    return np.concatenate([less, tied[:more]]), int(tied[more - 1]), np.concatenate([tied[more:], at[own > bound]])


def median_depth(parts: int) -> int:
    return math.ceil(math.log2(max(parts, 1)))


def medians(points: np.ndarray, hashes: np.ndarray, parts: int, rule: str = "depth", level: int = 0) -> Layout:
    """Median cuts, axes in turn, to the depth of ``parts`` leaves or ("capacity") to their mean size. ``level``: cuts made already."""
    d, tree, leaves, n = points.shape[1], Tree(), [], len(points)
    depth, most = median_depth(parts), math.ceil(n / max(parts, 1))

    def build(at: np.ndarray, level: int) -> int:
        done = level == depth if rule == "depth" else len(at) <= most
        if done or len(at) < 2:
            leaves.append(at)
            return -len(leaves)
        axis = level % d
        low, last, high = _parted(points, hashes, at, axis, (len(at) + 1) // 2)
        node = tree.add(axis, _key(points, hashes, last, axis))
        tree.lo[node] = build(low, level + 1)
        tree.hi[node] = build(high, level + 1)
        return node

    build(np.arange(n), level)
    return _layout("kd", points, tree, leaves)


def quadrants(points: np.ndarray, hashes: np.ndarray, most: int, depth: int = 24) -> Layout:
    """Cells of more than ``most`` points are halved on every axis at once."""
    d, tree, leaves = points.shape[1], Tree(), []

    def build(at: np.ndarray, low: np.ndarray, high: np.ndarray, level: int, axis: int) -> int:
        if axis == 0 and (len(at) <= most or level == depth):
            leaves.append(at)
            return -len(leaves)
        middle = (low[axis] + high[axis]) / 2
        below = points[at, axis] <= middle
        node = tree.add(axis, [float(middle), *[math.inf] * d])
        left_high, right_low = high.copy(), low.copy()
        left_high[axis] = right_low[axis] = middle
        after = (axis + 1) % d
        deeper = level + (after == 0)
        tree.lo[node] = build(at[below], low, left_high, deeper, after)
        tree.hi[node] = build(at[~below], right_low, high, deeper, after)
        return node

    build(np.arange(len(points)), points.min(axis=0), points.max(axis=0), 0, 0)
    return _layout("quad", points, tree, leaves)


def cells(low: np.ndarray, high: np.ndarray, parts: int) -> Tree:
    """The tree of a grid of equal cells over an extent."""
    d, tree, made = len(low), Tree(), []
    f = fan_out(parts, d)

    def build(axis: int) -> int:
        if axis == d:
            made.append(axis)
            return -len(made)
        edges = [low[axis] + (high[axis] - low[axis]) * i / f for i in range(1, f)]
        return _binary(tree, axis, [[float(e), *[math.inf] * d] for e in edges], [build(axis + 1) for _ in range(f)])

    build(0)
    return _rooted(tree)


def uniform(points: np.ndarray, hashes: np.ndarray, parts: int) -> Layout:
    """A grid of equal cells."""
    tree = cells(points.min(axis=0), points.max(axis=0), parts)
    at = tree.route(points, hashes)
    order = np.argsort(at, kind="stable")
    return _layout("grid", points, tree, np.split(order, np.searchsorted(at[order], np.arange(1, len(tree.axis) + 1))))


@dataclass
class CurveLayout:
    """Runs of a curve: partition i holds the keys above i cuts."""

    method: str
    low: list[float]
    high: list[float]
    bits: int
    cuts: list[int]

    @property
    def parts(self) -> int:
        return len(self.cuts) + 1

    def extent(self, d: int) -> tuple[list[float], list[float]]:
        return self.low, self.high

    def cells(self, points: np.ndarray) -> np.ndarray:
        low, high = np.array(self.low), np.array(self.high)
        top = (1 << self.bits) - 1
        span = np.where(high > low, high - low, 1.0)
        return np.clip(np.floor((points - low) / span * top), 0, top).astype(np.int64)

    def keys(self, points: np.ndarray) -> np.ndarray:
        return (z_key_np if self.method == "z" else hilbert_key_np)(self.cells(points), self.bits)

    def route(self, points: np.ndarray, hashes: np.ndarray | None = None) -> np.ndarray:
        return np.searchsorted(np.array(self.cuts, np.int64), self.keys(points), "left")


def curve_runs(points: np.ndarray, parts: int, method: str = "z", bits: int | None = None) -> CurveLayout:
    """Equal-count runs of the sample along a curve."""
    layout = CurveLayout(method, points.min(axis=0).tolist(), points.max(axis=0).tolist(), bits or curve_bits(points.shape[1]), [])
    keys = np.sort(layout.keys(points))
    at = [len(keys) * i // parts - 1 for i in range(1, parts)]
    layout.cuts = sorted({int(keys[i]) for i in at if i >= 0})
    return layout
