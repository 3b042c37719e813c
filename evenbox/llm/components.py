"""Connected components by alternating star contraction, DataFrame operations only.

Each round hangs every node's larger neighbours below its smallest neighbour, then every node and its
smaller neighbours below the smallest of them. Rows never outnumber the edges, the smallest node of
a component ends as its root, and the rounds needed grow with the logarithm of the input. Rounds
are written to the shared folder, so a lost executor costs one round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.llm.scratch import Scratch


def _state(edges: DataFrame) -> tuple:
    """Row count and an order-free checksum: equal after a round if nothing moved."""
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").bitwiseAND(F.lit((1 << 31) - 1)))).first()
    return row[0], row[1]


def connected_components(edges: DataFrame, scratch: Scratch, label: str) -> DataFrame:
    """``edges`` (a, b) -> (node, root) for every node that has an edge; root is the smallest node.

    Loops, repeated edges, either direction and nulls (ignored) are allowed; no edges, no rows.
    """
    now = edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    now = scratch.write(now, f"{label}-0")
    state, turn = _state(now), 0
    while state[0]:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        lowest = large.groupBy("a").agg(F.min("b").alias("m"))
        below = large.join(lowest, "a")
        small = below.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(lowest.withColumnRenamed("m", "b")).distinct()
        turn += 1
        now = scratch.write(small, f"{label}-{turn}")
        scratch.drop(f"{label}-{turn - 1}")
        before, state = state, _state(now)
        if before == state:
            break
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
