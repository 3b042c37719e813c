"""Phase 3 routing: records to partitions, as column expressions.

The tree is one row of arrays, broadcast; its size grows with the number of partitions, a few dozen bytes each.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenbox.functions import geom
from evenbox.functions.curves import hilbert_udf, lattice, z_key
from evenbox.operators.phase1 import valid
from evenbox.plans.baselines import CurveLayout
from evenbox.plans.grow import Layout, Tree

#: leaves up to which the CASE form stays inside one compiled method
CASE_LEAVES = 128
#: cuts of a curve that a record is compared with one by one
CURVE_CUTS = 64
#: copies of boxes that are sent on at once
COPIES = 20_000


def tree_frame(spark: SparkSession, tree: Tree) -> DataFrame:
    """One row: axis, cut, lo, hi."""
    row = pa.table({"axis": pa.array([tree.axis], pa.list_(pa.int32())), "cut": pa.array([tree.cut], pa.list_(pa.list_(pa.float64()))), "lo": pa.array([tree.lo], pa.list_(pa.int32())), "hi": pa.array([tree.hi], pa.list_(pa.int32()))})
    return spark.createDataFrame(row)


def _rotations(axes: Sequence[str]) -> Column:
    d = len(axes)
    return F.array(*[F.array(*[F.col(axes[(a + j) % d]).cast("double") for j in range(d)], F.col("kh")) for a in range(d)])


def route_points(df: DataFrame, tree: Tree, axes: Sequence[str] = ("x", "y"), mode: str = "tree") -> DataFrame:
    """``df`` with part_id by descent of the tree; nulls and NaN go to -1.

    mode: "tree" folds over the levels, "case" is nested CASE for small trees, "arrow" is numpy by batch. All three agree.
    """
    ok = valid(axes)
    if not tree.axis:
        return df.withColumn("part_id", F.when(ok, F.lit(0)).otherwise(F.lit(-1)))
    if mode == "case":
        return df.withColumn("part_id", F.when(ok, _case(tree, axes, 0)).otherwise(F.lit(-1)))
    if mode == "arrow":
        return _route_arrow(df, tree, axes)
    named = tree_frame(df.sparkSession, tree).select(F.struct("axis", "cut", "lo", "hi").alias("_tree"))
    t = F.col("_tree")
    step = lambda node, _: F.when(node < 0, node).otherwise(F.when(F.get(F.col("_turns"), F.get(t["axis"], node)) <= F.get(t["cut"], node), F.get(t["lo"], node)).otherwise(F.get(t["hi"], node)))
    leaf = F.aggregate(F.sequence(F.lit(1), F.lit(max(tree.depth(), 1))), F.lit(0), step)
    routed = df.withColumn("_turns", _rotations(axes)).crossJoin(F.broadcast(named))
    return routed.withColumn("part_id", F.when(ok, -(leaf + 1)).otherwise(F.lit(-1)).cast("int")).drop("_turns", "_tree")


def _case(tree: Tree, axes: Sequence[str], node: int) -> Column:
    if node < 0:
        return F.lit(-(node + 1))
    d, a = len(axes), tree.axis[node]
    keys = [F.col(axes[(a + j) % d]).cast("double") for j in range(d)] + [F.col("kh")]
    low = F.lit(True)
    for key, bound in reversed(list(zip(keys, tree.cut[node], strict=True))):
        low = F.lit(True) if math.isinf(bound) else (key < bound) | ((key == bound) & low)
    return F.when(low, _case(tree, axes, tree.lo[node])).otherwise(_case(tree, axes, tree.hi[node]))


def _route_arrow(df: DataFrame, tree: Tree, axes: Sequence[str]) -> DataFrame:
    schema = df.withColumn("part_id", F.lit(0)).schema
    tree = Tree(np.array(tree.axis), np.array(tree.cut), np.array(tree.lo), np.array(tree.hi))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(a).cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False) for a in (*axes, "kh")]
            data = np.column_stack(columns)
            ok = ~np.isnan(data[:, :-1]).any(axis=1)
            out = np.full(len(data), -1, np.int32)
            out[ok] = tree.route(data[ok, :-1], data[ok, -1])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], [*batch.schema.names, "part_id"])

    return df.mapInArrow(run, schema)


def _with_leaves(df: DataFrame, tree: Tree, lo: Sequence[str], hi: Sequence[str]) -> DataFrame:
    """``df`` with _leaves, the leaf regions its box meets (closed on both sides)."""
    if not tree.axis:
        return df.withColumn("_leaves", F.array(F.lit(0)))
    named = tree_frame(df.sparkSession, tree).select(F.struct("axis", F.transform("cut", lambda c: c[0]).alias("cut"), "lo", "hi").alias("_tree"))
    t = F.col("_tree")
    low, high = F.array(*[F.col(c).cast("double") for c in lo]), F.array(*[F.col(c).cast("double") for c in hi])

    def children(node: Column) -> Column:
        a, c = F.get(t["axis"], node), F.get(t["cut"], node)
        down = F.when(F.get(F.col("_low"), a) <= c, F.array(F.get(t["lo"], node))).otherwise(F.array().cast("array<int>"))
        up = F.when(F.get(F.col("_high"), a) >= c, F.array(F.get(t["hi"], node))).otherwise(F.array().cast("array<int>"))
        return F.when(node < 0, F.array(node)).otherwise(F.concat(down, up))

    front = F.aggregate(F.sequence(F.lit(1), F.lit(tree.depth())), F.array(F.lit(0)), lambda nodes, _: F.flatten(F.transform(nodes, children)))
    routed = df.withColumns({"_low": low, "_high": high}).crossJoin(F.broadcast(named))
    return routed.withColumn("_leaves", F.transform(front, lambda n: -(n + 1))).drop("_tree", "_low", "_high")


def route_boxes(df: DataFrame, tree: Tree, lo: Sequence[str], hi: Sequence[str], mode: str = "tree") -> DataFrame:
    """A row of ``df`` for every leaf region its box meets (closed on both sides): the replicated, disjoint layout.

    mode: "tree" folds over the levels, "arrow" is numpy by batch; both agree on boxes without nulls and NaN, which "arrow" leaves out.
    """
    if mode == "arrow" and tree.axis:
        return _boxes_arrow(df, tree, lo, hi)
    return _with_leaves(df, tree, lo, hi).withColumn("part_id", F.explode("_leaves")).drop("_leaves")


def _boxes_arrow(df: DataFrame, tree: Tree, lo: Sequence[str], hi: Sequence[str]) -> DataFrame:
    schema = df.withColumn("part_id", F.lit(0)).schema
    axis, cut, low_child, high_child = np.array(tree.axis), np.array([c[0] for c in tree.cut]), np.array(tree.lo), np.array(tree.hi)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            low, high = (np.column_stack([batch.column(c).cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False) for c in names]) for names in (lo, hi))
            row = np.flatnonzero(~np.isnan(low).any(axis=1) & ~np.isnan(high).any(axis=1))
            node, rows, leaves = np.zeros(len(row), np.int64), [], []
            while len(row):
                a, c = axis[node], cut[node]
                down, up = low[row, a] <= c, high[row, a] >= c
                row, node = np.concatenate([row[down], row[up]]), np.concatenate([low_child[node[down]], high_child[node[up]]])
                done = node < 0
                rows.append(row[done])
                leaves.append(-(node[done] + 1))
                row, node = row[~done], node[~done]
            if not rows:
                continue
            held = batch.take(pa.array(np.concatenate(rows)))
            part = pa.array(np.concatenate(leaves).astype(np.int32))
            for i in range(0, held.num_rows, COPIES):  # a batch becomes many copies
                yield pa.RecordBatch.from_arrays([*held.slice(i, COPIES).columns, part.slice(i, COPIES)], [*batch.schema.names, "part_id"])

    return df.mapInArrow(run, schema)


def route_auto(df: DataFrame, tree: Tree, boxes: DataFrame, lo: Sequence[str], hi: Sequence[str], by: str = "area") -> DataFrame:
    """One partition for each record: the box that alone contains it, if there is one; else that of least enlargement among the
    leaves whose regions the record meets. Only that shortlist is looked at, so a record costs the depth of the tree.

    ``boxes`` (part_id from 0 without gaps, blo, bhi) becomes one array of a row for each partition.
    """
    one = boxes.agg(F.array_sort(F.collect_list(F.struct("part_id", "blo", "bhi"))).alias("_boxes"))
    d = len(lo)
    at = lambda i: F.get(F.col("_boxes"), i)
    ends = lambda b: ([b["blo"][i] for i in range(d)], [b["bhi"][i] for i in range(d)])

    def cost(i: Column) -> Column:
        blo, bhi = ends(at(i))
        own = (geom.volume if by == "area" else geom.margin)(blo, bhi)
        return F.struct(geom.enlargement(blo, bhi, geom.cols(lo), geom.cols(hi), by).alias("grow"), own.alias("own"), i.alias("part_id"))

    holding = F.filter("_leaves", lambda i: geom.contains(*ends(at(i)), geom.cols(lo), geom.cols(hi)))
    routed = _with_leaves(df, tree, lo, hi).crossJoin(F.broadcast(one)).withColumn("_in", holding)
    place = F.when(F.size("_in") == 1, F.get("_in", F.lit(0))).otherwise(F.array_min(F.transform("_leaves", cost))["part_id"])
    return routed.withColumn("part_id", place).drop("_leaves", "_boxes", "_in")


def route_anchor(df: DataFrame, tree: Tree, lo: Sequence[str], hi: Sequence[str]) -> DataFrame:
    """Extended records without copies: each goes where the centre of its box goes."""
    axes = [f"_a{i}" for i in range(len(lo))]
    centres = dict(zip(axes, geom.centre(geom.cols(lo), geom.cols(hi)), strict=True))
    return route_points(df.withColumns(centres), tree, axes).drop(*axes)


def route_enlarge(df: DataFrame, boxes: DataFrame, lo: Sequence[str], hi: Sequence[str], by: str = "area") -> DataFrame:
    """Least enlargement of a partition's volume or margin, then the smaller measure, then the lower id.

    ``boxes`` (part_id, blo, bhi arrays) becomes one array, so a record looks at all of them without a shuffle; for a thousand boxes or so.
    """
    one = boxes.agg(F.collect_list(F.struct("part_id", "blo", "bhi")).alias("_boxes"))
    d = len(lo)

    def cost(b: Column) -> Column:
        blo, bhi = [b["blo"][i] for i in range(d)], [b["bhi"][i] for i in range(d)]
        own = (geom.volume if by == "area" else geom.margin)(blo, bhi)
        return F.struct(geom.enlargement(blo, bhi, geom.cols(lo), geom.cols(hi), by).alias("grow"), own.alias("own"), b["part_id"].alias("part_id"))

    routed = df.crossJoin(F.broadcast(one))
    return routed.withColumn("part_id", F.array_min(F.transform("_boxes", cost))["part_id"]).drop("_boxes")


def route_overlap(df: DataFrame, boxes: DataFrame, lo: Sequence[str], hi: Sequence[str]) -> DataFrame:
    """Least growth of overlap with the sibling boxes, then enlargement, area, id; every pair of boxes is looked at, so for few boxes."""
    one = boxes.agg(F.collect_list(F.struct("part_id", "blo", "bhi")).alias("_boxes"))
    d = len(lo)

    def shared(alo, ahi, o: Column) -> Column:
        return geom.overlap_volume(alo, ahi, [o["blo"][i] for i in range(d)], [o["bhi"][i] for i in range(d)])

    def cost(b: Column) -> Column:
        blo, bhi = [b["blo"][i] for i in range(d)], [b["bhi"][i] for i in range(d)]
        ulo, uhi = geom.union_box(blo, bhi, geom.cols(lo), geom.cols(hi))
        growth = F.aggregate(F.filter("_boxes", lambda o: o["part_id"] != b["part_id"]), F.lit(0.0), lambda acc, o: acc + (shared(ulo, uhi, o) - shared(blo, bhi, o)).cast("double"))
        return F.struct(growth.alias("overlap"), geom.enlargement(blo, bhi, geom.cols(lo), geom.cols(hi)).alias("grow"), geom.volume(blo, bhi).alias("own"), b["part_id"].alias("part_id"))

    routed = df.crossJoin(F.broadcast(one))
    return routed.withColumn("part_id", F.array_min(F.transform("_boxes", cost))["part_id"]).drop("_boxes")


def curve_key(layout: CurveLayout, axes: Sequence[str]) -> Column:
    """The key of the Z-curve is a column expression; Hilbert's is an Arrow function."""
    cells = [lattice(F.col(a), lo, hi, layout.bits) for a, lo, hi in zip(axes, layout.low, layout.high, strict=True)]
    return z_key(cells, layout.bits) if layout.method == "z" else hilbert_udf(layout.bits)(F.array(*cells))


def _curve_arrow(df: DataFrame, layout: CurveLayout, axes: Sequence[str]) -> DataFrame:
    schema = df.withColumn("part_id", F.lit(0)).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data = np.column_stack([batch.column(a).cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False) for a in axes])
            ok = ~np.isnan(data).any(axis=1)
            out = np.full(len(data), -1, np.int32)
            out[ok] = layout.route(data[ok])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], [*batch.schema.names, "part_id"])

    return df.mapInArrow(run, schema)


def route_curve(df: DataFrame, layout: CurveLayout, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """Partition = cuts below the record's curve key; keys and many cuts, searched by halves, are for numpy, by batch."""
    if len(layout.cuts) > CURVE_CUTS:
        return _curve_arrow(df, layout, axes)
    key = curve_key(layout, axes)
    cuts = F.array(*[F.lit(c).cast("long") for c in layout.cuts]) if layout.cuts else F.array().cast("array<long>")
    keyed = df.withColumn("_key", key)
    return keyed.withColumn("part_id", F.when(valid(axes), F.size(F.filter(cuts, lambda c: c < F.col("_key")))).otherwise(F.lit(-1))).drop("_key")


def route(df: DataFrame, layout: Layout | CurveLayout, axes: Sequence[str] = ("x", "y"), mode: str = "tree") -> DataFrame:
    """Route by whatever the layout has: curve cuts, a tree of cuts, or only boxes (least margin enlargement)."""
    if isinstance(layout, CurveLayout):
        return route_curve(df, layout, axes)
    if layout.tree.axis or layout.parts <= 1:
        return route_points(df, layout.tree, axes, mode)
    return route_enlarge(df, box_frame(df.sparkSession, layout), axes, axes, "margin")


def box_frame(spark: SparkSession, layout: Layout) -> DataFrame:
    rows = [(i, [float(x) for x in lo], [float(x) for x in hi]) for i, (lo, hi) in sorted(layout.boxes.items())]
    return spark.createDataFrame(rows, "part_id int, blo array<double>, bhi array<double>")


def regions(spark: SparkSession, tree: Tree, d: int) -> DataFrame:
    rows = [(i, lo, hi) for i, (lo, hi) in sorted(tree.regions(d).items())]
    return spark.createDataFrame(rows, "part_id int, rlo array<double>, rhi array<double>")
