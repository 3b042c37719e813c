"""Quality and cost measures of a layout, from its manifest.

Manifest: part_id, n_rows, bytes, and lo_/hi_ columns of every axis (the box of the records that are there). A
partition counts once for each of its blocks, for each block is a task.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenbox.functions import geom
from evenbox.operators.meeting import CellGrid, meeting


def manifest(routed: DataFrame, axes: Sequence[str] = ("x", "y"), block: int | None = None) -> DataFrame:
    ends = [f(a).alias(f"{n}_{a}") for a in axes for n, f in (("lo", F.min), ("hi", F.max))]
    out = routed.where("part_id >= 0").groupBy("part_id").agg(F.count("*").alias("n_rows"), F.sum("bytes").alias("bytes"), *ends)
    return with_blocks(out, block) if block else out


def box_manifest(routed: DataFrame, lo: Sequence[str], hi: Sequence[str], names: Sequence[str] = ("x", "y")) -> DataFrame:
    ends = [c for a, low, high in zip(names, lo, hi, strict=True) for c in (F.min(low).alias(f"lo_{a}"), F.max(high).alias(f"hi_{a}"))]
    return routed.groupBy("part_id").agg(F.count("*").alias("n_rows"), F.sum("bytes").alias("bytes"), *ends)


def with_blocks(man: DataFrame, block: int) -> DataFrame:
    return man.withColumn("blocks", F.ceil(F.col("bytes") / block).cast("long"))


def _ends(axes: Sequence[str], alias: str = "") -> tuple[list, list]:
    dot = f"{alias}." if alias else ""
    return [F.col(f"{dot}lo_{a}") for a in axes], [F.col(f"{dot}hi_{a}") for a in axes]


def _names(axes: Sequence[str], side: str) -> tuple[list[str], list[str]]:
    return [f"lo_{a}_{side}" for a in axes], [f"hi_{a}_{side}" for a in axes]


def _sided(man: DataFrame, axes: Sequence[str], side: str) -> DataFrame:
    """A manifest's ids, blocks and ends under names of one side of a join."""
    ends = [F.col(f"{e}_{a}").alias(f"{e}_{a}_{side}") for a in axes for e in ("lo", "hi")]
    blocks = [F.col("blocks").alias(f"blocks_{side}")] if "blocks" in man.columns else []
    return man.select(F.col("part_id").alias(f"part_{side}"), *blocks, *ends)


def _asked(queries: DataFrame, man: DataFrame, axes: Sequence[str]) -> DataFrame:
    """Queries (qid, qlo_/qhi_) with the partitions that they meet."""
    held = man.select("part_id", *[c for c in ("blocks", "n_rows") if c in man.columns], *[f"{e}_{a}" for a in axes for e in ("lo", "hi")])
    return meeting(queries, held, ([f"qlo_{a}" for a in axes], [f"qhi_{a}" for a in axes]), ([f"lo_{a}" for a in axes], [f"hi_{a}" for a in axes]))


def total_volume(man: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    return man.agg(F.sum(F.col("blocks") * geom.volume(*_ends(axes))).alias("volume"))


def total_margin(man: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    return man.agg(F.sum(F.col("blocks") * geom.margin(*_ends(axes))).alias("margin"))


#: boxes of a cell beyond which their pairs are made in blocks of this many, rather than joined row by row
CROWDED = 512


def total_overlap(man: DataFrame, axes: Sequence[str] = ("x", "y"), ordered: bool = False) -> DataFrame:
    """Shared volume over pairs of blocks, those of one partition included. ordered: both orders of a pair of partitions count.

    Pairs of partitions meet on the cells of a grid. Those of a cell with many (boxes that cover the whole extent share one) are made
    in blocks, each a small task.
    """
    sided = _sided(man, axes, "a")
    grid = CellGrid(sided, *_names(axes, "a"))
    cells = [f"_acell{i}" for i in range(grid.d)]
    dealt = grid.dealt(sided, *_names(axes, "a"), "a").withColumn("_held", F.count("*").over(Window.partitionBy(*cells)))
    few = dealt.where(F.col("_held") <= CROWDED).drop("_held")
    other = few.toDF(*[c.replace("_acell", "_bcell").replace("_afirst", "_bfirst") if c.startswith("_a") else f"{c.removesuffix('_a')}_b" for c in few.columns])
    pairs = few.join(other, grid.same_cells()).where(grid.once() & (F.col("part_a") < F.col("part_b")))
    shared = geom.overlap_volume(*[[F.col(c) for c in side] for x in "ab" for side in _names(axes, x)])
    times = 2 if ordered else 1
    across = pairs.select((F.col("blocks_a") * F.col("blocks_b") * shared * times).cast("double").alias("v"))
    crowd = _crowded_overlap(dealt.where(F.col("_held") > CROWDED), axes, grid.d).select((F.col("v") * times).alias("v"))
    own = man.select((F.expr("blocks * (blocks - 1) / 2") * geom.volume(*_ends(axes))).cast("double").alias("v"))
    return across.unionByName(crowd).unionByName(own).agg(F.coalesce(F.sum("v"), F.lit(0.0)).alias("overlap"))


def _crowded_overlap(dealt: DataFrame, axes: Sequence[str], d: int) -> DataFrame:
    """v: of blocks of boxes that share a cell (first in ``once``'s sense), the shared volume over their pairs of partitions."""
    cells, (low, high) = [f"_acell{i}" for i in range(d)], _names(axes, "a")
    blocks = F.ceil(F.col("_held") / CROWDED).cast("int")
    own = dealt.withColumn("_own", F.pmod(F.xxhash64("part_a"), blocks).cast("int")).withColumn("_with", F.explode(F.sequence(F.lit(0), blocks - 1)))
    tiles = own.withColumns({"_i": F.least("_own", "_with"), "_j": F.greatest("_own", "_with")})

    def of(table: pa.Table) -> pa.Table:
        column = {c: table.column(c).to_numpy() for c in ("_own", "_i", "_j", "blocks_a", *low, *high, *cells, *[f"_afirst{i}" for i in range(d)])}
        a, b = column["_own"] == column["_i"][0], column["_own"] == column["_j"][0]
        v = np.multiply.outer(column["blocks_a"][a].astype(float), column["blocks_a"][b].astype(float))
        for i in range(d):
            first = column[f"_afirst{i}"]
            v *= np.maximum.outer(first[a], first[b]) == column[f"_acell{i}"][0]
        for lo, hi in zip(low, high, strict=True):
            v *= np.maximum(np.minimum.outer(column[hi][a], column[hi][b]) - np.maximum.outer(column[lo][a], column[lo][b]), 0)
        total = v.sum() if column["_i"][0] != column["_j"][0] else np.triu(v, 1).sum()
        return pa.table({"v": [float(total)]})

    return tiles.groupBy(*cells, "_i", "_j").applyInArrow(of, "v double")


def utilisation(man: DataFrame, block: int) -> DataFrame:
    return man.agg((F.sum("bytes") / (F.sum("blocks") * block)).alias("utilisation"))


def size_deviation(man: DataFrame) -> DataFrame:
    return man.agg(F.stddev_pop("bytes").alias("deviation"))


def load_stats(man: DataFrame) -> DataFrame:
    return man.agg(F.count("*").alias("parts"), F.sum("blocks").alias("blocks"), F.min("n_rows").alias("min_rows"), F.max("n_rows").alias("max_rows"), (F.min("bytes") / F.max("bytes")).alias("fill"))


def all_measures(man: DataFrame, block: int, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """One row with every measure."""
    one = man.agg(
        F.count("*").alias("parts"), F.sum("blocks").alias("blocks"), F.sum(F.col("blocks") * geom.volume(*_ends(axes))).alias("volume"),
        F.sum(F.col("blocks") * geom.margin(*_ends(axes))).alias("margin"), (F.sum("bytes") / (F.sum("blocks") * block)).alias("utilisation"), F.stddev_pop("bytes").alias("deviation"),
    )
    return one.crossJoin(total_overlap(man, axes))


def range_cost(man: DataFrame, queries: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """qid, blocks, parts: what each query box (qlo_/qhi_ columns) has to read."""
    met = _asked(queries, man, axes).select("qid", "blocks", "part_id")
    every = queries.select("qid", F.lit(0).cast("long").alias("blocks"), F.lit(None).cast("int").alias("part_id")).unionByName(met)
    return every.groupBy("qid").agg(F.sum("blocks").alias("blocks"), F.count("part_id").alias("parts"))


def join_cost(left: DataFrame, right: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """Of a join of two manifests: partition pairs, block pairs, block reads, distinct blocks."""
    met = meeting(_sided(left, axes, "a"), _sided(right, axes, "b"), _names(axes, "a"), _names(axes, "b"))
    met = met.select(F.col("part_a").alias("pa"), F.col("blocks_a").alias("ba"), F.col("part_b").alias("pb"), F.col("blocks_b").alias("bb"))
    once = met.select(F.struct(F.lit(0).alias("side"), F.col("pa").alias("p")).alias("k"), F.col("ba").alias("n")).unionByName(met.select(F.struct(F.lit(1).alias("side"), F.col("pb").alias("p")).alias("k"), F.col("bb").alias("n"))).distinct()
    sums = met.agg(F.count("*").alias("pairs"), F.coalesce(F.sum(F.col("ba") * F.col("bb")), F.lit(0)).alias("block_pairs"), F.coalesce(F.sum(F.col("ba") + F.col("bb")), F.lit(0)).alias("block_reads"))
    return sums.crossJoin(once.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("distinct_blocks")))


def prune_report(man: DataFrame, queries: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """Partitions that a query misses, contains, or only touches."""
    qlo, qhi = [F.col(f"qlo_{a}") for a in axes], [F.col(f"qhi_{a}") for a in axes]
    met = _asked(queries, man, axes).select("qid", geom.contains(qlo, qhi, *_ends(axes)).alias("inside"))
    every = queries.select("qid", F.lit(None).cast("boolean").alias("inside")).unionByName(met)
    met = every.groupBy("qid").agg(F.count("inside").alias("met"), F.coalesce(F.sum(F.col("inside").cast("long")), F.lit(0)).alias("contained"))
    total = man.agg(F.count("*").alias("n"))  # one row
    return met.crossJoin(F.broadcast(total)).select("qid", (F.col("n") - F.col("met")).alias("pruned"), "contained", (F.col("met") - F.col("contained")).alias("boundary"))


def replication(man: DataFrame, records: int) -> DataFrame:
    return man.agg((F.sum("n_rows") / records).alias("replication"))


def overview(results: DataFrame, measures: Sequence[str]) -> DataFrame:
    """Each measure over its largest among the methods of a workload; utilisation stays as it is."""
    every = Window.partitionBy("workload")
    scaled = [(F.col(m) / F.max(m).over(every)).alias(m) for m in measures if m != "utilisation"]
    return results.select("workload", "method", *scaled, *[m for m in measures if m == "utilisation"])


def repeat_stats(results: DataFrame, keys: Sequence[str], measures: Sequence[str]) -> DataFrame:
    return results.groupBy(*keys).agg(*[f(m).alias(f"{n}_{m}") for m in measures for n, f in (("mean", F.avg), ("sd", F.stddev_samp))])


def needs_rebuild(man: DataFrame, theta: float = 0.5) -> DataFrame:
    """Whether sizes have drifted: deviation over mean above theta."""
    ratio = F.stddev_pop("bytes") / F.avg("bytes")
    return man.agg(ratio.alias("ratio"), (ratio > theta).alias("rebuild"))
