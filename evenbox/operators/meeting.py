"""Pairs of boxes that meet, by an equi-join on the cells of a grid; each pair once."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.functions import geom

#: axes that cells are made of; the others are tested on the pairs
CELL_AXES = 3
MOST_CELLS = 1 << 10


class CellGrid:
    """A grid over the boxes of a table, with a cell for each box at most, and cells no narrower than the mean box (nor than ``least``): boxes
    that cover most of an axis get few cells there. What lies outside belongs to the outermost cells."""

    def __init__(self, boxes: DataFrame, lo: Sequence[str], hi: Sequence[str], least: Sequence[float] | None = None):
        spread = [(F.min(a), F.max(b), F.avg(F.col(b).cast("double") - F.col(a).cast("double"))) for a, b in zip(lo, hi, strict=True)]
        row = boxes.agg(F.count("*").alias("n"), *[c.alias(f"{n}{i}") for i, ends in enumerate(spread) for n, c in zip(("lo", "hi", "mean"), ends, strict=True)]).first()
        self.rows = row["n"]
        low = [float(row[f"lo{i}"] or 0.0) for i in range(len(lo))]
        width = [float((row[f"hi{i}"] or 0.0) - (row[f"lo{i}"] or 0.0)) or 1.0 for i in range(len(lo))]
        #: of the mean box
        self.mean = [float(row[f"mean{i}"] or 0.0) for i in range(len(lo))]
        wide = [max(m, w) for m, w in zip(self.mean, least or [0.0] * len(lo), strict=True)]
        fits = [w / m if m else float("inf") for w, m in zip(width, wide, strict=True)]
        #: the axes that the mean box covers least of
        self.axes = sorted(sorted(range(len(lo)), key=lambda i: (-fits[i], i))[:CELL_AXES])
        self.d = len(self.axes)
        cells, left = {}, max(1, self.rows)
        for k, i in enumerate(sorted(self.axes, key=lambda i: fits[i])):
            cells[i] = max(1, min(MOST_CELLS, round(left ** (1 / (self.d - k))), int(min(fits[i], MOST_CELLS))))
            left = max(1, left / cells[i])
        self.cells, self.low, self.width = ([v[i] for i in self.axes] for v in (cells, low, width))

    def cell(self, value: Column, i: int) -> Column:
        place = F.floor((value.cast("double") - self.low[i]) / self.width[i] * self.cells[i])
        return F.greatest(F.lit(0), F.least(F.lit(self.cells[i] - 1), place)).cast("int")

    def dealt(self, boxes: DataFrame, lo: Sequence[Column | str], hi: Sequence[Column | str], tag: str) -> DataFrame:
        """A row for each cell that a box covers: _<tag>cell<i>, and the box's first cell _<tag>first<i>."""
        for i, axis in enumerate(self.axes):
            low, high = (F.col(c) if isinstance(c, str) else c for c in (lo[axis], hi[axis]))
            first = self.cell(low, i)
            boxes = boxes.withColumns({f"_{tag}first{i}": first, f"_{tag}cell{i}": F.sequence(first, F.greatest(first, self.cell(high, i)))})
        for i in range(self.d):
            boxes = boxes.withColumn(f"_{tag}cell{i}", F.explode(f"_{tag}cell{i}"))
        return boxes

    def placed(self, boxes: DataFrame, lo: Sequence[Column | str], tag: str) -> DataFrame:
        """The same with the first cell only."""
        for i, axis in enumerate(self.axes):
            first = self.cell(F.col(lo[axis]) if isinstance(lo[axis], str) else lo[axis], i)
            boxes = boxes.withColumns({f"_{tag}first{i}": first, f"_{tag}cell{i}": first})
        return boxes

    def once(self) -> Column:
        """Of the cells that two boxes share, the first."""
        return reduce(lambda x, y: x & y, [F.col(f"_acell{i}") == F.greatest(f"_afirst{i}", f"_bfirst{i}") for i in range(self.d)])

    def same_cells(self) -> Column:
        return reduce(lambda x, y: x & y, [F.col(f"_acell{i}") == F.col(f"_bcell{i}") for i in range(self.d)])

    def names(self) -> list[str]:
        return [f"_{tag}{kind}{i}" for tag in "ab" for kind in ("first", "cell") for i in range(self.d)]


def meeting(left: DataFrame, right: DataFrame, left_ends: tuple[Sequence[str], Sequence[str]], right_ends: tuple[Sequence[str], Sequence[str]]) -> DataFrame:
    """The rows of ``left`` and ``right`` whose boxes (names of low and high columns) meet. No column has the same name on both sides.

    The grid follows ``right``. Two boxes may share many cells; they are a pair in the first of them.
    """
    grid = CellGrid(right, *right_ends)
    pairs = grid.dealt(left, *left_ends, "a").join(grid.dealt(right, *right_ends, "b"), grid.same_cells())
    boxes = [[F.col(c) for c in side] for side in (*left_ends, *right_ends)]
    return pairs.where(grid.once() & geom.overlaps(*boxes)).drop(*grid.names())
