"""An R*-tree built record by record, for comparison: its leaves' boxes make the layout.

Choose the child that grows least (overlap above the leaves, area elsewhere), reinsert the farthest entries
the first time a level overflows, else split by least margin, overlap and area.
"""

from __future__ import annotations

import numpy as np

from evenbox.plans.cut import Counters
from evenbox.plans.grow import Layout, Tree


class _Box:
    __slots__ = ("children", "high", "level", "low", "parent")

    def __init__(self, low, high, level, children=None, parent=None):
        self.low, self.high, self.level, self.children, self.parent = low, high, level, children if children is not None else [], parent

    def fit(self) -> None:
        self.low = np.min([c.low for c in self.children], axis=0)
        self.high = np.max([c.high for c in self.children], axis=0)


def _volume(low, high):
    return np.prod(np.maximum(high - low, 0), axis=-1)


class InsertTree:
    def __init__(self, least: int, most: int, reinsert: float = 0.3):
        self.least, self.most, self.share = least, most, reinsert
        self.root: _Box | None = None
        self.again: set[int] = set()

    def insert(self, point: np.ndarray) -> None:
        self.again = set()
        self._put(_Box(point, point, -1))

    def _put(self, entry: _Box) -> None:
        if self.root is None:
            self.root = _Box(entry.low, entry.high, 0)
        node = self.root
        while node.level > entry.level + 1:
            node = self._choose(node, entry)
        entry.parent = node
        node.children.append(entry)
        self._grow(node, entry)
        if len(node.children) > self.most:
            self._overflow(node)

    def _grow(self, node: _Box | None, entry: _Box) -> None:
        while node is not None:
            node.low, node.high = np.minimum(node.low, entry.low), np.maximum(node.high, entry.high)
            node = node.parent

    def _choose(self, node: _Box, entry: _Box) -> _Box:
        low, high = np.array([c.low for c in node.children]), np.array([c.high for c in node.children])
        new_low, new_high = np.minimum(low, entry.low), np.maximum(high, entry.high)
        area = _volume(low, high)
        growth = _volume(new_low, new_high) - area
        first = growth
        if node.level == 1:
            def shared(a, b):
                return _volume(np.maximum(a[:, None], low[None]), np.minimum(b[:, None], high[None])).sum(axis=1)

            first = (shared(new_low, new_high) - _volume(new_low, new_high)) - (shared(low, high) - area)
        return node.children[int(np.lexsort((np.arange(len(area)), area, growth, first))[0])]

    def _overflow(self, node: _Box) -> None:
        if node.parent is not None and node.level not in self.again:
            self.again.add(node.level)
            centre = (node.low + node.high) / 2
            far = np.argsort([-np.sum(((c.low + c.high) / 2 - centre) ** 2) for c in node.children], kind="stable")
            out = [node.children[i] for i in far[: max(1, int(self.share * len(node.children)))]]
            node.children = [c for c in node.children if all(c is not o for o in out)]
            up = node
            while up is not None:
                up.fit()
                up = up.parent
            for entry in reversed(out):
                self._put(entry)
            return
        self._split(node)

    def _split(self, node: _Box) -> None:
        low, high = np.array([c.low for c in node.children]), np.array([c.high for c in node.children])
        best = None
        for axis in range(low.shape[1]):
            order = np.lexsort((high[:, axis], low[:, axis]))
            a_low, a_high = np.minimum.accumulate(low[order]), np.maximum.accumulate(high[order])
            b_low, b_high = np.minimum.accumulate(low[order][::-1])[::-1], np.maximum.accumulate(high[order][::-1])[::-1]
            k = np.arange(self.least, len(order) - self.least + 1)
            margins = (a_high - a_low)[k - 1].sum() + (b_high - b_low)[k].sum()
            overlap = _volume(np.maximum(a_low[k - 1], b_low[k]), np.minimum(a_high[k - 1], b_high[k]))
            area = _volume(a_low[k - 1], a_high[k - 1]) + _volume(b_low[k], b_high[k])
            at = int(np.lexsort((k, area, overlap))[0])
            if best is None or margins < best[0]:
                best = (margins, order, int(k[at]))
        _, order, k = best
        entries = [node.children[i] for i in order]
        node.children = entries[:k]
        node.fit()
        twin = _Box(None, None, node.level, entries[k:], node.parent)
        twin.fit()
        for c in twin.children:
            c.parent = twin
        if node.parent is None:
            self.root = _Box(np.minimum(node.low, twin.low), np.maximum(node.high, twin.high), node.level + 1, [node, twin])
            node.parent = twin.parent = self.root
            return
        node.parent.children.append(twin)
        if len(node.parent.children) > self.most:
            self._overflow(node.parent)

    def leaves(self) -> list[_Box]:
        out, stack = [], [self.root] if self.root else []
        while stack:
            node = stack.pop()
            if node.level == 0:
                out.append(node)
            else:
                stack += node.children
        return out


def rstar_insert(points: np.ndarray, least: int, most: int, reinsert: float = 0.3) -> Layout:
    """Leaves of a tree after inserting the points in order; boxes may overlap and there is no tree of cuts."""
    tree = InsertTree(max(1, min(least, (most + 1) // 2)), max(most, 2), reinsert)
    for p in points:
        tree.insert(p)
    leaves = tree.leaves()
    boxes = {i: (leaf.low.tolist(), leaf.high.tolist()) for i, leaf in enumerate(leaves)}
    counts = {i: len(leaf.children) for i, leaf in enumerate(leaves)}
    return Layout("rstar_insert", Tree(), boxes, {i: float(n) for i, n in counts.items()}, counts, Counters())
