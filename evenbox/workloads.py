"""All registered queries, and the flagship."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evenbox.cases import engine_cases, method_cases, query_cases  # noqa: F401
from evenbox.operators import quality, router
from evenbox.operators.learn import learn
from evenbox.registry import QUERIES, SQL, Query
from evenbox.sources import tables


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``documents`` in byte-balanced partitions of 32 KiB: the manifest with the measures."""
    docs = tables.points(spark, sf_dir, "documents_hash")
    block = 32 << 10
    layout = learn(docs, "mbs_bytes", block).layout
    man = quality.manifest(router.route(docs, layout), block=block)
    return man.crossJoin(quality.all_measures(man, block).withColumnRenamed("blocks", "total_blocks"))


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
