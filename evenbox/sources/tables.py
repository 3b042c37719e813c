"""The given tables as spatial fixtures, and their DuckDB twins.

Every point fixture has its key columns, x, y (doubles), bytes (bigint) and kh, a hash of the key in [0, 1) by whole-number
arithmetic that any engine repeats. Times become whole days since 1995-01-01 or epoch seconds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MODULUS = 1000003
#: multipliers of the key hash; fixed values
MULTIPLIERS = (2654435761, 40503, 7919, 104729)
LINE_KEYS = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def key_mix(*keys: str) -> str:
    """SQL for a whole number in 0..MODULUS-1 that both engines compute alike."""
    return "((" + " + ".join(f"CAST({k} AS BIGINT) * {m}" for k, m in zip(keys, MULTIPLIERS, strict=False)) + f") % {MODULUS})"


def key_hash(*keys: str) -> str:
    return f"(CAST({key_mix(*keys)} AS DOUBLE) / {MODULUS}.0)"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_DAYS = {"spark": "CAST(datediff(CAST({0} AS DATE), DATE'1995-01-01') AS {1})", "duck": "CAST(date_diff('day', DATE '1995-01-01', CAST({0} AS DATE)) AS {1})"}
_SECONDS = {"spark": "CAST(timestampdiff(SECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', {0}) AS {1})", "duck": "CAST(date_diff('second', TIMESTAMP '1970-01-01 00:00:00', {0}) AS {1})"}
_BYTES = {"spark": "CAST(octet_length({0}) AS BIGINT)", "duck": "CAST(strlen({0}) AS BIGINT)"}


def days(column: str, engine: str, kind: str = "DOUBLE") -> str:
    return _DAYS[engine].format(column, kind)


def seconds(column: str, engine: str, kind: str = "DOUBLE") -> str:
    return _SECONDS[engine].format(column, kind)


def octets(column: str, engine: str) -> str:
    return _BYTES[engine].format(column)


def _blanks(column: str) -> str:
    return f"(CAST(length({column}) - length(replace({column}, ' ', '')) AS DOUBLE) / greatest(length({column}), 1))"


def fixture_parts(name: str, engine: str) -> tuple[str, tuple[str, ...], str, str, str]:
    """(table, keys, x, y, bytes) of a point fixture in the SQL of an engine."""
    return {
        "lineitem": ("lineitem", LINE_KEYS, "l_extendedprice", days("l_shipdate", engine), "CAST(100 AS BIGINT)"),
        "orders": ("orders", ("o_orderkey",), "o_totalprice", days("o_orderdate", engine), "CAST(100 AS BIGINT)"),
        "events": ("events", ("event_id",), seconds("ts", engine), "value", "CAST(100 AS BIGINT)"),
        "documents": ("documents", ("doc_id",), "CAST(n_chars AS DOUBLE)", _blanks("text"), octets("text", engine)),
        "documents_hash": ("documents", ("doc_id",), "CAST((doc_id * 7919 + 13) % 10007 AS DOUBLE)", "CAST((doc_id * 104729 + 71) % 10009 AS DOUBLE)", octets("text", engine)),
        "pages": ("pages", ("page_id",), "CAST(length(html) AS DOUBLE)", "(CAST(length(html) - length(replace(html, '<', '')) AS DOUBLE) / greatest(length(html), 1))", octets("html", engine)),
    }[name]


def point_keys(name: str) -> tuple[str, ...]:
    return fixture_parts(name, "spark")[1]


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A point fixture; only the columns it needs are read."""
    table, keys, x, y, size = fixture_parts(name, "spark")
    return load(spark, sf_dir, table).selectExpr(*keys, f"{x} AS x", f"{y} AS y", f"{size} AS bytes", f"{key_hash(*keys)} AS kh")


def points_sql(name: str) -> str:
    table, keys, x, y, size = fixture_parts(name, "duck")
    return f"SELECT {', '.join(keys)}, {x} AS x, {y} AS y, {size} AS bytes, {key_hash(*keys)} AS kh FROM {table}"


#: attributes of the mixed-attribute fixture; prefixes of 4, 5 and 7 are used
TRIP_AXES = ("l_extendedprice", "l_quantity", "l_discount", "l_tax", "ship_day", "o_totalprice", "order_day")


def trips(spark: SparkSession, sf_dir: str, d: int) -> DataFrame:
    """Order lines with d attributes as axes a0.."""
    lines, orders = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    joined = lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]) if d > 5 else lines
    columns = {"ship_day": days("l_shipdate", "spark"), "order_day": days("o_orderdate", "spark")}
    return joined.selectExpr(*LINE_KEYS, *[f"{columns.get(a, a)} AS a{i}" for i, a in enumerate(TRIP_AXES[:d])], "CAST(100 AS BIGINT) AS bytes", f"{key_hash(*LINE_KEYS)} AS kh")


def diagonal_sql(d: int, perc: int = 50, buf: int = 100) -> list[str]:
    """d coordinates in thousandths of a million: ``perc`` per thousand lie on the diagonal, others off by up to ``buf`` / 2 thousandths.

    Whole numbers only: a linear-congruential mix of the key, the same in both engines.
    """
    u = f"({key_mix(*LINE_KEYS)})"
    step = lambda i: f"(({u} * {48271 + 2 * i} + {i} * 7919 + 11) % {MODULUS})"
    off = lambda i: f"((({step(i + 1)} % {buf * 1000}) - {buf * 500}))"
    base = f"({u} * 1000000 // {MODULUS})"
    diagonal = f"({step(0)} % 1000 < {perc})"
    return [f"CASE WHEN {diagonal} THEN {base} ELSE greatest(0, least(1000000, {base} + {off(i)})) END" for i in range(d)]


def diagonal(spark: SparkSession, sf_dir: str, d: int) -> DataFrame:
    mix = key_mix(*LINE_KEYS)
    axes = [f"CAST({x.replace('//', 'DIV').replace(mix, '_u')} AS DOUBLE) AS a{i}" for i, x in enumerate(diagonal_sql(d))]
    mixed = load(spark, sf_dir, "lineitem").selectExpr(*LINE_KEYS, f"{mix} AS _u")
    # a generator of one row: filters on the axes would repeat their expressions, too long then to be compiled
    made = mixed.selectExpr(*LINE_KEYS, "_u", f"inline(array(struct({', '.join(axes)})))")
    return made.selectExpr(*LINE_KEYS, *[f"a{i}" for i in range(d)], "CAST(100 AS BIGINT) AS bytes", f"{key_hash(*LINE_KEYS).replace(mix, '_u')} AS kh")


def vectors(spark: SparkSession, sf_dir: str, d: int) -> DataFrame:
    """The first d entries of the embeddings."""
    return load(spark, sf_dir, "embeddings").selectExpr("vec_id", *[f"CAST(embedding[{i}] AS DOUBLE) AS a{i}" for i in range(d)], "CAST(100 AS BIGINT) AS bytes", f"{key_hash('vec_id')} AS kh", "label")


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A segment from each event of a user to the user's next, with its box."""
    from pyspark.sql import Window

    events = load(spark, sf_dir, "events").selectExpr("user_id", "event_id", f"{seconds('ts', 'spark', 'BIGINT')} AS t", "CAST(round(value * 100) AS BIGINT) AS v")
    order = Window.partitionBy("user_id").orderBy("t", "event_id")
    ends = events.select("*", F.lead("t").over(order).alias("t2"), F.lead("v").over(order).alias("v2")).where("t2 is not null")
    return ends.select("user_id", "event_id", F.col("t").alias("sx"), F.col("v").alias("sy"), F.col("t2").alias("ex"), F.col("v2").alias("ey"), F.least("t", "t2").alias("x1"), F.least("v", "v2").alias("y1"), F.greatest("t", "t2").alias("x2"), F.greatest("v", "v2").alias("y2"))


SEGMENTS_SQL = f"""SELECT user_id, event_id, t AS sx, v AS sy, t2 AS ex, v2 AS ey, least(t, t2) AS x1, least(v, v2) AS y1, greatest(t, t2) AS x2, greatest(v, v2) AS y2
FROM (SELECT user_id, event_id, t, v, lead(t) OVER w AS t2, lead(v) OVER w AS v2 FROM (SELECT user_id, event_id, {seconds('ts', 'duck', 'BIGINT')} AS t, CAST(round(value * 100) AS BIGINT) AS v FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY t, event_id)) WHERE t2 IS NOT NULL"""


def hour_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The box of the events of each type in each hour."""
    events = load(spark, sf_dir, "events").selectExpr("event_type", f"{seconds('ts', 'spark', 'BIGINT')} AS t", "CAST(round(value * 100) AS BIGINT) AS v")
    return events.groupBy("event_type", F.floor(F.col("t") / 3600).alias("hour")).agg(F.min("t").alias("x1"), F.min("v").alias("y1"), F.max("t").alias("x2"), F.max("v").alias("y2"), F.count("*").alias("n"))


HOUR_BOXES_SQL = f"""SELECT event_type, t // 3600 AS hour, min(t) AS x1, min(v) AS y1, max(t) AS x2, max(v) AS y2, count(*) AS n
FROM (SELECT event_type, {seconds('ts', 'duck', 'BIGINT')} AS t, CAST(round(value * 100) AS BIGINT) AS v FROM events) GROUP BY 1, 2"""
