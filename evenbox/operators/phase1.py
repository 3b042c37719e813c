"""Phase 1: summary, sample, byte histogram and point weights."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.sources.tables import MODULUS

#: sample points the driver takes in at most; larger samples grow on the executors
DRIVER_POINTS = 5_000_000


def summarize(df: DataFrame, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """One row: rows, bytes, and the extent of every axis. One scan; min, max and count come from footers where the source allows."""
    extent = [f(a).alias(f"{n}_{a}") for a in axes for n, f in (("min", F.min), ("max", F.max))]
    return df.agg(F.count("*").alias("n_rows"), F.sum("bytes").alias("n_bytes"), *extent)


def valid(axes: Sequence[str]) -> Column:
    """No axis is null or NaN; other records go to the reserved partition -1."""
    flags = [F.col(a).isNotNull() & ~F.isnan(F.col(a).cast("double")) for a in axes]
    out = flags[0]
    for flag in flags[1:]:
        out = out & flag
    return out


def sample_fraction(df: DataFrame, ratio: float, seed: int = 1) -> DataFrame:
    return df.sample(False, ratio, seed) if ratio < 1 else df


def sample_by_hash(df: DataFrame, ratio: float, seed: int = 0) -> DataFrame:
    """Rows whose key hash, turned by the seed, is below the ratio: the same rows however the files lie."""
    if ratio >= 1:
        return df
    turned = F.pmod(F.round(F.col("kh") * MODULUS).cast("long") * (2 * seed + 1) + seed * 7919, F.lit(MODULUS))
    return df.where(turned < int(ratio * MODULUS))


def sample_capped(df: DataFrame, n: int, keys: Sequence[str]) -> DataFrame:
    """The n rows of least hash; top-n in every task, so no full sort."""
    return df.orderBy("kh", *keys).limit(n)


def byte_histogram(df: DataFrame, low: Sequence[float], high: Sequence[float], grid: Sequence[int], axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """(cell, bytes, n) of the non-empty cells of a uniform grid; partial sums are made before the shuffle."""
    return df.groupBy(cell_number(low, high, grid, axes).alias("cell")).agg(F.sum("bytes").alias("bytes"), F.count("*").alias("n"))


def cell_number(low: Sequence[float], high: Sequence[float], grid: Sequence[int], axes: Sequence[str] = ("x", "y")) -> Column:
    cell = F.lit(0).cast("long")
    for a, lo, hi, g in zip(axes, low, high, grid, strict=True):
        span = (hi - lo) or 1.0
        cell = cell * g + F.greatest(F.lit(0), F.least(F.lit(g - 1), F.floor((F.col(a) - lo) / span * g))).cast("long")
    return cell


def weigh(sample: DataFrame, histogram: DataFrame, cell: Column, orphans: str = "nearest", grid: Sequence[int] | None = None) -> DataFrame:
    """``sample`` with w: its cell's bytes over its cell's sample points. Bytes of cells without a point go to the
    nearest cell with one, are spread by rescaling, or are dropped. The histogram has at most grid cells, so it is broadcast."""
    marked = sample.withColumn("cell", cell)
    counts = marked.groupBy("cell").agg(F.count("*").alias("k"))
    held = histogram.join(F.broadcast(counts), "cell", "left")
    if orphans == "nearest":
        homes = counts.select(F.col("cell").alias("home"))
        lost = held.where("k is null").select("cell", "bytes")
        moved = lost.crossJoin(F.broadcast(homes)).groupBy("cell", "bytes").agg(F.min_by("home", F.struct(_cell_distance(grid), F.col("home"))).alias("home"))
        more = moved.groupBy(F.col("home").alias("cell")).agg(F.sum("bytes").alias("more"))
        held = held.where("k is not null").join(F.broadcast(more), "cell", "left").withColumn("bytes", F.col("bytes") + F.coalesce("more", F.lit(0)))
    else:
        held = held.where("k is not null")
    weighted = marked.join(F.broadcast(held.select("cell", (F.col("bytes") / F.col("k")).alias("w"))), "cell", "left").fillna({"w": 0.0})
    if orphans == "rescale":
        whole = histogram.agg(F.sum("bytes").alias("_all"))
        kept = held.agg(F.sum("bytes").alias("_kept"))
        weighted = weighted.crossJoin(F.broadcast(whole)).crossJoin(F.broadcast(kept)).withColumn("w", F.col("w") * F.col("_all") / F.col("_kept")).drop("_all", "_kept")
    return weighted


def _cell_distance(grid: Sequence[int]) -> Column:
    """Squared distance of cell and home in cells."""
    total, a, b = F.lit(0).cast("long"), F.col("cell"), F.col("home")
    for g in reversed(grid):
        step = F.pmod(a, F.lit(g)) - F.pmod(b, F.lit(g))
        total = total + step * step
        a, b = F.floor(a / g), F.floor(b / g)
    return total


def default_grid(n: int, d: int) -> list[int]:
    """About four sample points in a non-empty cell."""
    return [int(min(64, max(2, round((max(n, 1) / 4) ** (1 / d)))))] * d


def to_numpy(sample: DataFrame, axes: Sequence[str], weight: str | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """(points, hashes, weights) on the driver, in an order that does not depend on the layout of the files; refuses more than ``DRIVER_POINTS``."""
    columns = [*axes, "kh", *([weight] if weight else [])]
    table = sample.select(*[F.col(c).cast("double") for c in columns]).limit(DRIVER_POINTS + 1).toArrow()
    if table.num_rows > DRIVER_POINTS:
        raise ValueError(f"the sample has more than {DRIVER_POINTS} points: lower the ratio or grow on the executors")
    data = np.column_stack([table[i].to_numpy() for i in range(len(columns))]) if table.num_rows else np.zeros((0, len(columns)))
    data = data[np.lexsort(data.T[::-1])]
    d = len(axes)
    return data[:, :d].copy(), data[:, d].copy(), data[:, d + 1].copy() if weight else None
