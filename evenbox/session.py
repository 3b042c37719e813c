"""Session settings that every plan here assumes."""

from __future__ import annotations

from pyspark.sql import SparkSession


def session(name: str = "evenbox", master: str | None = None, **conf: str) -> SparkSession:
    """A session with UTC time, AQE with skew joins, and block-sized scan splits."""
    builder = SparkSession.builder.appName(name)
    if master:
        builder = builder.master(master)
    settings = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.parquet.aggregatePushdown": "true",
        "spark.sql.files.maxPartitionBytes": "128m",
    } | conf
    for key, value in settings.items():
        builder = builder.config(key, value)
    return builder.getOrCreate()
