"""Joins of two partitioned sets of boxes.

The partitions' boxes are joined first; each record is sent to those partition pairs whose other box it can find a partner
in, and an equi-join on the pair and on the cell of a grid, with the exact predicate as its residual, finds the record pairs.
With single-copy layouts every record pair belongs to exactly one partition pair, and in it counts in the first cell that both
share. With a replicated layout a pair is kept only in the region that the lower corner of its common box falls into.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.functions import geom
from evenbox.operators import quality
from evenbox.operators.meeting import CellGrid, meeting
from evenbox.operators.router import regions, route_boxes, route_points
from evenbox.plans.grow import Tree

LO, HI = ("x1", "y1"), ("x2", "y2")
_SHARED = ("_lo0", "_lo1"), ("_hi0", "_hi1")


def predicate(kind: str, distance: float = 0.0, a: str = "a", b: str = "b") -> Column:
    """intersects, contains (a holds b), within (b holds a) or distance (gap of the boxes at most ``distance`` on every axis)."""
    side = lambda t, names: [F.col(f"{t}.{n}") for n in names]
    first, second = (side(a, LO), side(a, HI)), (side(b, LO), side(b, HI))
    if kind == "intersects":
        return geom.overlaps(*first, *second)
    if kind == "contains":
        return geom.contains(*first, *second)
    if kind == "within":
        return geom.contains(*second, *first)
    if kind == "distance":
        grown = [c - distance for c in first[0]], [c + distance for c in first[1]]
        return geom.overlaps(*grown, *second)
    raise ValueError(f"no predicate {kind}")


def pair_partitions(left: DataFrame, right: DataFrame, distance: float = 0.0) -> DataFrame:
    """(pa, pb, pair) of partitions whose boxes meet, and the ends of both (those of a grown by the distance); inputs are manifests with lo_/hi_ columns."""
    axes = ("x", "y")
    a, b = quality._sided(left, axes, "a"), quality._sided(right, axes, "b")
    a = a.withColumns({f"lo_{x}_a": F.col(f"lo_{x}_a") - distance for x in axes} | {f"hi_{x}_a": F.col(f"hi_{x}_a") + distance for x in axes})
    ends = [quality._names(axes, side) for side in "ab"]
    met = meeting(a, b, *ends)
    return met.select(F.col("part_a").alias("pa"), F.col("part_b").alias("pb"), (F.col("part_a").cast("long") * (1 << 32) + F.col("part_b")).alias("pair"), *[n for side in ends for names in side for n in names])


def _sent(df: DataFrame, pairs: DataFrame, side: str, kind: str, reach: float = 0.0) -> DataFrame:
    """Records with ``pair``, for the pairs in whose other partition they can have a partner: where boxes only meet, their own box (grown
    by ``reach``) meets the other partition's; where the other side holds them, the other partition holds them. _lo and _hi are the ends
    of what both boxes share."""
    other = "b" if side == "a" else "a"
    names = quality._names(("x", "y"), other)
    ends = [[F.col(n) for n in group] for group in names]
    own = [F.col(c) - reach for c in LO], [F.col(c) + reach for c in HI]
    held = (kind, side) in (("within", "a"), ("contains", "b"))
    sent = df.join(pairs.select(f"p{side}", "pair", *names[0], *names[1]), F.col("part_id") == F.col(f"p{side}"))
    return _clipped(sent.where(geom.contains(*ends, *own) if held else geom.overlaps(*ends, *own)), own, ends).drop(f"p{side}", *names[0], *names[1])


def _clipped(df: DataFrame, own: tuple[Sequence[Column], Sequence[Column]], ends: tuple[Sequence[Column], Sequence[Column]]) -> DataFrame:
    """``df`` with the ends of the common box of two as _lo0, _lo1, _hi0, _hi1."""
    low = {f"_lo{i}": F.greatest(a.cast("double"), b.cast("double")) for i, (a, b) in enumerate(zip(own[0], ends[0], strict=True))}
    return df.withColumns(low | {f"_hi{i}": F.least(a.cast("double"), b.cast("double")) for i, (a, b) in enumerate(zip(own[1], ends[1], strict=True))})


def spatial_join(left: DataFrame, right: DataFrame, kind: str = "intersects", distance: float = 0.0, how: str = "inner", local: str = "hash", left_keys: Sequence[str] = (), right_keys: Sequence[str] = ()) -> DataFrame:
    """Join two routed, single-copy sides (part_id, x1, y1, x2, y2, ...).

    how: inner, left_semi, left_anti, left. local: "hash" is an equi-join on cells with residual, "sweep" a plane sweep in each pair.
    Columns of the result: the keys of both sides (of the left side for semi and anti).
    """
    reach = distance if kind == "distance" else 0.0
    pairs = pair_partitions(quality.box_manifest(left, LO, HI), quality.box_manifest(right, LO, HI), reach)
    a = _sent(left, pairs, "a", kind, reach)
    b = _sent(right, pairs, "b", kind)  # the ends of a are grown already
    if local == "sweep":
        found = _swept(a, b, left_keys, right_keys, kind, reach)
    else:
        wide = [v + 2 * reach for v in CellGrid(left, LO, HI).mean] if kind not in ("within", "contains") else None
        grid = CellGrid(right, LO, HI, wide)
        # a box that is held lies in one cell with its lower corner, so it is looked for there alone
        a = grid.placed(a, LO, "a") if kind == "within" else grid.dealt(a, *_SHARED, "a")
        b = grid.placed(b, LO, "b") if kind == "contains" else grid.dealt(b, *_SHARED, "b")
        once = F.lit(True) if kind in ("within", "contains") else grid.once()
        found = a.alias("a").join(b.alias("b"), (F.col("a.pair") == F.col("b.pair")) & grid.same_cells() & once & predicate(kind, distance))
        found = found.select(*[F.col(f"a.{k}") for k in left_keys], *[F.col(f"b.{k}") for k in right_keys])
    if how == "inner":
        return found
    keys = left.select(*left_keys)
    if how in ("left_semi", "left_anti"):
        return keys.join(found.select(*left_keys).distinct(), list(left_keys), how)
    return keys.join(found, list(left_keys), "left")


def _swept(a: DataFrame, b: DataFrame, left_keys: Sequence[str], right_keys: Sequence[str], kind: str, reach: float) -> DataFrame:
    kinds = dict(a.dtypes) | dict(b.dtypes)
    schema = ", ".join(f"{k} {kinds[k]}" for k in (*left_keys, *right_keys))

    def sweep(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        """Both sides in order of their low x; for each box of one side, those of the other that begin inside it."""
        x, y = x.sort_values("x1"), y.sort_values("x1")
        xs, ys = x[list(LO + HI)].to_numpy(float), y[list(LO + HI)].to_numpy(float)
        xs = xs + np.array([-reach, -reach, reach, reach])
        out_i, out_j = [], []
        begin, end = np.searchsorted(ys[:, 0], xs[:, 0], "left"), np.searchsorted(ys[:, 0], xs[:, 2], "right")
        for i in range(len(xs)):
            j = np.arange(begin[i], end[i])
            out_j.append(j)
            out_i.append(np.full(len(j), i))
        begin, end = np.searchsorted(xs[:, 0], ys[:, 0], "right"), np.searchsorted(xs[:, 0], ys[:, 2], "right")
        for j in range(len(ys)):
            i = np.arange(begin[j], end[j])
            out_i.append(i)
            out_j.append(np.full(len(i), j))
        i, j = (np.concatenate(v) if v else np.zeros(0, int) for v in (out_i, out_j))
        p, q = xs[i], ys[j]
        if kind == "contains":
            ok = (p[:, 0] <= q[:, 0]) & (p[:, 1] <= q[:, 1]) & (q[:, 2] <= p[:, 2]) & (q[:, 3] <= p[:, 3])
        elif kind == "within":
            ok = (q[:, 0] <= p[:, 0]) & (q[:, 1] <= p[:, 1]) & (p[:, 2] <= q[:, 2]) & (p[:, 3] <= q[:, 3])
        else:
            ok = (p[:, 0] <= q[:, 2]) & (q[:, 0] <= p[:, 2]) & (p[:, 1] <= q[:, 3]) & (q[:, 1] <= p[:, 3])
        left, right = x.iloc[i[ok]][list(left_keys)].reset_index(drop=True), y.iloc[j[ok]][list(right_keys)].reset_index(drop=True)
        return pd.concat([left, right], axis=1)

    left, right = a.select("pair", *left_keys, *LO, *HI), b.select(F.col("pair").alias("pair_b"), *right_keys, *LO, *HI)
    return left.groupBy("pair").cogroup(right.groupBy("pair_b")).applyInPandas(sweep, schema)


def coarsened(tree: Tree, mean: Sequence[float]) -> Tree:
    """The tree without the cuts below which a region would be narrower than the mean box: finer regions only multiply the copies of boxes."""
    out = Tree()

    def build(node: int, low: list[float], high: list[float]) -> int:
        a, c = (tree.axis[node], tree.cut[node]) if node >= 0 else (0, [])
        if node < 0 or min(high[a] - c[0], c[0] - low[a]) < mean[a]:
            leaves.append(node)
            return -len(leaves)
        at = out.add(a, list(c))
        out.lo[at] = build(tree.lo[node], low, [c[0] if i == a else v for i, v in enumerate(high)])
        out.hi[at] = build(tree.hi[node], [c[0] if i == a else v for i, v in enumerate(low)], high)
        return at

    leaves: list[int] = []
    build(0 if len(tree.axis) else -1, [-np.inf] * len(mean), [np.inf] * len(mean))
    return out


def replicated(df: DataFrame, tree: Tree, regions: DataFrame) -> DataFrame:
    """A copy for each region that a record's box meets, with the ends of the region."""
    return route_boxes(df, tree, LO, HI, "arrow").join(regions, "part_id")


def join_copartitioned(left: DataFrame, right: DataFrame, tree: Tree, left_keys: Sequence[str], right_keys: Sequence[str], kind: str = "intersects") -> DataFrame:
    """Both sides replicated to the regions of one tree, as far as they are no narrower than the mean box, and joined region by region on the
    cells of a grid; a pair counts in the region and the cell of the lower corner of its common box (a corner on a cut belongs below it)."""
    wide = CellGrid(left, LO, HI).mean
    grid = CellGrid(right, LO, HI, wide)
    tree = coarsened(tree, [max(a, b) for a, b in zip(wide, grid.mean, strict=True)])
    places = regions(left.sparkSession, tree, 2)
    sides = []
    for df, tag in ((left, "a"), (right, "b")):
        copies = _clipped(replicated(df, tree, places), (geom.cols(LO), geom.cols(HI)), [[F.col(c)[i] for i in range(2)] for c in ("rlo", "rhi")])
        sides.append(grid.dealt(copies, *_SHARED, tag).alias(tag))
    corner = [F.greatest(f"a.{c}", f"b.{c}").cast("double") for c in LO]
    here = geom.every([(c > F.col("a.rlo")[i]) & (c <= F.col("a.rhi")[i]) for i, c in enumerate(corner)])
    met = sides[0].join(sides[1], (F.col("a.part_id") == F.col("b.part_id")) & grid.same_cells() & grid.once() & here & predicate(kind))
    return met.select(*[F.col(f"a.{k}") for k in left_keys], *[F.col(f"b.{k}") for k in right_keys])


def join_broadcast(left: DataFrame, right: DataFrame, left_keys: Sequence[str], right_keys: Sequence[str], kind: str = "intersects", most: int = 100_000) -> DataFrame:
    """Every left record against a small right side; refuses one of more than ``most`` rows."""
    if right.limit(most + 1).count() > most:
        raise ValueError("the right side is too large to broadcast: partition both sides")
    met = left.alias("a").join(F.broadcast(right.alias("b")), predicate(kind))
    return met.select(*[F.col(f"a.{k}") for k in left_keys], *[F.col(f"b.{k}") for k in right_keys])


def range_boxes(replicated: DataFrame, tree: Tree, lo: Sequence[float], hi: Sequence[float]) -> DataFrame:
    """Records whose box meets a query box, from a replicated layout, each once and without a shuffle: only the copy where the lower corner of box and query is routed counts."""
    box = [F.lit(float(x)) for x in lo], [F.lit(float(x)) for x in hi]
    met = replicated.withColumnRenamed("part_id", "_here").where(geom.overlaps(geom.cols(LO), geom.cols(HI), *box))
    corner = met.withColumns({"_cx": F.greatest(F.col("x1").cast("double"), box[0][0]), "_cy": F.greatest(F.col("y1").cast("double"), box[0][1]), "kh": F.lit(0.0)})
    return route_points(corner, tree, ("_cx", "_cy")).where("part_id = _here").drop("_cx", "_cy", "kh", "_here", "part_id")


def dedup_distinct(replicated: DataFrame, keys: Sequence[str], lo: Sequence[float], hi: Sequence[float]) -> DataFrame:
    """The same by a shuffle on the keys."""
    box = [F.lit(float(x)) for x in lo], [F.lit(float(x)) for x in hi]
    return replicated.where(geom.overlaps(geom.cols(LO), geom.cols(HI), *box)).drop("part_id").dropDuplicates(list(keys))


def tile_counts(df: DataFrame, low: Sequence[float], high: Sequence[float], zooms: Sequence[int], axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """zoom, tx, ty, n, bytes: counts of square tiles at every zoom; the finest is counted from the records, the rest from it."""
    top = max(zooms)
    cell = lambda a, lo, hi: F.least(F.lit((1 << top) - 1), F.floor((F.col(a) - lo) / ((hi - lo) or 1.0) * (1 << top))).cast("long")
    fine = df.groupBy(*[cell(a, lo, hi).alias(t) for a, lo, hi, t in zip(axes, low, high, ("fx", "fy"), strict=True)]).agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes"))
    levels = fine.withColumn("zoom", F.explode(F.array(*[F.lit(z) for z in zooms])))
    return levels.groupBy("zoom", F.expr(f"shiftright(fx, {top} - zoom)").alias("tx"), F.expr(f"shiftright(fy, {top} - zoom)").alias("ty")).agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))

