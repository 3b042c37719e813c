"""Structured Streaming forms: route with a frozen tree, windowed histograms, drift, dedup, joins."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from evenbox.operators.router import route_points
from evenbox.plans.grow import Tree


def read_files(spark: SparkSession, path: str, schema, files_each: int = 4) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_each).parquet(path)


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run what is there to the end and give the result as a table: appended rows as files beside the checkpoint, so that they never
    come to the driver; complete and updated results, a row for each group, in memory."""
    files = f"{checkpoint}-rows"
    writer = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    query = writer.format("parquet").start(files) if mode == "append" else writer.format("memory").start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(files) if mode == "append" else stream.sparkSession.table(name)


def route_stream(stream: DataFrame, tree: Tree, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """Stateless: each record to the partition of a frozen tree."""
    return route_points(stream, tree, axes, "case")


def histogram_stream(stream: DataFrame, cell, window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Bytes and records of every cell in every tumbling window; records later than the watermark are dropped."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", window), cell.alias("cell")).agg(F.sum("bytes").alias("bytes"), F.count("*").alias("n"))


def dedup_stream(stream: DataFrame, keys: Sequence[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(list(keys))


def drift_stream(routed: DataFrame, theta: float = 0.5) -> DataFrame:
    """Per group, running record counts of its partitions; a row after each batch with their deviation over their mean, and whether it passes theta."""

    def update(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        counts = dict(zip(*state.get, strict=True)) if state.exists else {}
        for part in rows:
            for p, n in part.groupby("part_id")["bytes"].sum().items():
                counts[int(p)] = counts.get(int(p), 0) + int(n)
        state.update((list(counts), list(counts.values())))
        sizes = pd.Series(list(counts.values()), dtype=float)
        ratio = float(sizes.std(ddof=0) / sizes.mean()) if len(sizes) else 0.0
        yield pd.DataFrame({"grp": [key[0]], "parts": [len(sizes)], "bytes": [int(sizes.sum())], "ratio": [ratio], "rebuild": [ratio > theta]})

    return routed.groupBy("grp").applyInPandasWithState(update, "grp string, parts int, bytes long, ratio double, rebuild boolean", "parts array<int>, sizes array<long>", "update", GroupStateTimeout.NoTimeout)


def interval_join_stream(left: DataFrame, right: DataFrame, key: str, seconds: int, late: str = "1 hour") -> DataFrame:
    """Pairs of one key whose times are at most ``seconds`` apart; both sides are watermarked."""
    a, b = left.withWatermark("ts", late).alias("a"), right.withWatermark("ts", late).alias("b")
    near = F.expr(f"b.ts >= a.ts AND b.ts <= a.ts + INTERVAL {seconds} SECONDS")
    return a.join(b, (F.col(f"a.{key}") == F.col(f"b.{key}")) & near)
