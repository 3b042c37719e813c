"""Queries for the operators around the methods: formats, joins, aggregates, windows, sets, functions, streaming."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from evenbox.cases.method_cases import FIXED, VALID_RANGES_SQL, _FIXED_CASE, _routed
from evenbox.functions import geom
from evenbox.functions.sizing import cut_ranges
from evenbox.operators import phase1
from evenbox.registry import case
from evenbox.sources import tables as T
from evenbox.sources.io import DiagonalSource, parse_point, point_wkt, ring_box, work_path, write_formats
from evenbox.streaming import stream as S

Frame = DataFrame


# --- formats ----------------------------------------------------------------------------------------


def _formats(kind: str) -> None:
    def run(spark, sf_dir):
        df = T.points(spark, sf_dir, "events")
        path = write_formats(df, work_path(spark, "formats"))[kind]
        reader = spark.read.schema(df.schema)
        back = (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)
        return back.select("event_id", "x", "y", "bytes")

    case(f"scan_{kind}_roundtrip", f"SELECT event_id, x, y, bytes FROM ({T.points_sql('events')})")(run)


for _kind in ("csv", "json", "orc", "parquet"):
    _formats(_kind)


@case("wkt_roundtrip", f"SELECT event_id, x, y FROM ({T.points_sql('events')})")
def wkt_roundtrip(spark, sf_dir):
    text = T.points(spark, sf_dir, "events").select("event_id", point_wkt(F.col("x"), F.col("y")).alias("wkt"))
    x, y = parse_point(F.col("wkt"))
    return text.select("event_id", x.alias("x"), y.alias("y"))


@case("fn_wkt_parse", "SELECT hour, x1::DOUBLE AS x1, y1::DOUBLE AS y1, x2::DOUBLE AS x2, y2::DOUBLE AS y2 FROM (" + T.HOUR_BOXES_SQL + ")")
def fn_wkt_parse(spark, sf_dir):
    corner = lambda x, y: F.concat_ws(" ", x, y)
    ring = F.concat(F.lit("POLYGON(("), F.concat_ws(", ", corner("x1", "y1"), corner("x2", "y1"), corner("x2", "y2"), corner("x1", "y2"), corner("x1", "y1")), F.lit("))"))
    boxes = T.hour_boxes(spark, sf_dir).select("hour", ring.alias("wkt"))
    return boxes.select("hour", *[c.alias(n) for c, n in zip(ring_box(F.col("wkt")), ("x1", "y1", "x2", "y2"), strict=True)])


@case("source_diagonal")
def source_diagonal(spark, sf_dir):
    """A point near the diagonal for every order, from the Python source: its row with the order's key."""
    spark.dataSource.register(DiagonalSource)
    orders = T.load(spark, sf_dir, "orders").select("o_orderkey")
    rows = (orders.agg(F.max("o_orderkey")).first()[0] or 0) + 1
    points = spark.read.format("evenbox_diagonal").option("d", 4).option("rows", rows).load()
    return orders.join(points, orders["o_orderkey"] == points["id"]).select("o_orderkey", "c")


# --- filters ----------------------------------------------------------------------------------------

_L = "l_orderkey, l_linenumber, l_partkey, l_suppkey"


@case("filter_axes", f"SELECT {_L} FROM lineitem WHERE l_extendedprice BETWEEN 20000 AND 30000 AND l_quantity < 25")
def filter_axes(spark, sf_dir):
    return T.load(spark, sf_dir, "lineitem").where(F.col("l_extendedprice").between(20000, 30000) & (F.col("l_quantity") < 25)).select(*T.LINE_KEYS)


@case("filter_in", "SELECT event_id FROM events WHERE event_type IN ('click', 'view') AND props LIKE '%1%'")
def filter_in(spark, sf_dir):
    return T.load(spark, sf_dir, "events").where(F.col("event_type").isin("click", "view") & F.col("props").like("%1%")).select("event_id")


@case("filter_nulls", "SELECT count(*) AS n, CAST(sum(CASE WHEN props IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS missing FROM events WHERE value IS NOT NULL")
def filter_nulls(spark, sf_dir):
    return T.load(spark, sf_dir, "events").where("value is not null").agg(F.count("*").alias("n"), F.sum(F.col("props").isNull().cast("long")).alias("missing"))


@case("route_dirty", "SELECT part_id, count(*) AS n FROM (SELECT CASE WHEN l_orderkey % 10 < 2 THEN -1 ELSE " + _FIXED_CASE + f" END AS part_id FROM ({T.points_sql('lineitem')})) GROUP BY part_id")
def route_dirty(spark, sf_dir):
    """Null and NaN coordinates go to partition -1."""
    from evenbox.operators.router import route_points

    x = F.when(F.col("l_orderkey") % 10 == 0, F.lit(None)).when(F.col("l_orderkey") % 10 == 1, F.lit(float("nan"))).otherwise(F.col("x"))
    return route_points(T.points(spark, sf_dir, "lineitem").withColumn("x", x), FIXED).groupBy("part_id").agg(F.count("*").alias("n"))


# --- joins ------------------------------------------------------------------------------------------


def _tables(spark, sf_dir, *names):
    return [T.load(spark, sf_dir, n) for n in names]


@case("join_inner", "SELECT n_name, count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS keys FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_inner(spark, sf_dir):
    o, c, n = _tables(spark, sf_dir, "orders", "customer", "nation")
    return o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count("*").alias("n"), F.sum("o_custkey").alias("keys"))


@case("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY c_custkey")
def join_left(spark, sf_dir):
    c, o = _tables(spark, sf_dir, "customer", "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@case("join_full", "SELECT n_nationkey, s_suppkey FROM nation FULL JOIN (SELECT * FROM supplier WHERE s_nationkey < 10) s ON s_nationkey = n_nationkey")
def join_full(spark, sf_dir):
    n, s = _tables(spark, sf_dir, "nation", "supplier")
    s = s.where("s_nationkey < 10")
    return n.join(s, n.n_nationkey == s.s_nationkey, "full").select("n_nationkey", "s_suppkey")


@case("join_merge", "SELECT count(*) AS n, CAST(sum(l_suppkey) AS BIGINT) AS keys FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_totalprice > 200000")
def join_merge(spark, sf_dir):
    li, o = _tables(spark, sf_dir, "lineitem", "orders")
    return li.join(o.where("o_totalprice > 200000").hint("merge"), li.l_orderkey == o.o_orderkey).agg(F.count("*").alias("n"), F.sum("l_suppkey").alias("keys"))


for _how, _op in (("semi", "IN"), ("anti", "NOT IN")):
    case(f"join_{_how}_keys", f"SELECT c_custkey FROM customer WHERE c_custkey {_op} (SELECT o_custkey FROM orders WHERE o_totalprice > 400000)")(
        lambda spark, sf_dir, how=_how: T.load(spark, sf_dir, "customer").join(T.load(spark, sf_dir, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), f"left_{how}").select("c_custkey")
    )


@case("join_cross_small", "SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross_small(spark, sf_dir):
    r, n = _tables(spark, sf_dir, "region", "nation")
    return r.crossJoin(F.broadcast(n)).select("r_name", "n_name")


@case("join_interval", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 600 SECOND")
def join_interval(spark, sf_dir):
    e = T.load(spark, sf_dir, "events").select("user_id", "event_id", "ts")
    a, b = e.alias("a"), e.alias("b")
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & F.expr("b.ts > a.ts AND b.ts <= a.ts + INTERVAL 600 SECONDS")).select(F.col("a.event_id").alias("first_id"), F.col("b.event_id").alias("second_id"))


@case("join_asof", """SELECT event_id, last_click FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_click FROM events) WHERE event_type = 'purchase'""")
def join_asof(spark, sf_dir):
    """The last click of the user at or before each purchase: one sorted pass, no pairs."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    return T.load(spark, sf_dir, "events").withColumn("last_click", F.last(click, ignorenulls=True).over(order)).where("event_type = 'purchase'").select("event_id", "last_click")


@case("join_lateral_topk", "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS nth FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer)) WHERE nth <= 2")
def join_lateral_topk(spark, sf_dir):
    """The top two orders of every customer."""
    c, o = _tables(spark, sf_dir, "customer", "orders")
    top = o.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return c.lateralJoin(top).select("c_custkey", "o_orderkey")


# --- aggregates -------------------------------------------------------------------------------------


@case("agg_box_union", "SELECT event_type, min(x1) AS x1, min(y1) AS y1, max(x2) AS x2, max(y2) AS y2 FROM (" + T.HOUR_BOXES_SQL + ") GROUP BY event_type")
def agg_box_union(spark, sf_dir):
    return T.hour_boxes(spark, sf_dir).groupBy("event_type").agg(F.min("x1").alias("x1"), F.min("y1").alias("y1"), F.max("x2").alias("x2"), F.max("y2").alias("y2"))


@case("agg_centroid", f"SELECT l_linenumber, round(avg(CAST(round(x * 100) AS BIGINT)), 3) AS cx, round(avg(CAST(y AS BIGINT)), 6) AS cy FROM ({T.points_sql('lineitem')}) GROUP BY l_linenumber")
def agg_centroid(spark, sf_dir):
    return T.points(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(F.round(F.avg(F.round(F.col("x") * 100).cast("long")), 3).alias("cx"), F.round(F.avg(F.col("y").cast("long")), 6).alias("cy"))


for _name, _by in (("rollup", "ROLLUP (o_orderpriority, y)"), ("cube", "CUBE (o_orderpriority, y)")):
    case(f"agg_{_name}", f"SELECT o_orderpriority, y, count(*) AS n FROM (SELECT o_orderpriority, CAST(year(o_orderdate) AS INTEGER) AS y FROM orders) GROUP BY {_by}")(
        lambda spark, sf_dir, how=_name: getattr(T.load(spark, sf_dir, "orders").select("o_orderpriority", F.year("o_orderdate").alias("y")), how)("o_orderpriority", "y").agg(F.count("*").alias("n"))
    )


@case("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_grouping_sets(spark, sf_dir):
    li = T.load(spark, sf_dir, "lineitem")
    return li.groupingSets([[li.l_returnflag], [li.l_linestatus], []], li.l_returnflag, li.l_linestatus).agg(F.count("*").alias("n"))


@case("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def agg_distinct(spark, sf_dir):
    return T.load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@case("agg_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
def agg_pivot(spark, sf_dir):
    return T.load(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().fillna(0)


@case("agg_min_by", "SELECT o_orderpriority, min(o_orderkey) AS o_orderkey FROM orders WHERE (o_orderpriority, o_totalprice) IN (SELECT o_orderpriority, max(o_totalprice) FROM orders GROUP BY 1) GROUP BY 1")
def agg_min_by(spark, sf_dir):
    return T.load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.max_by("o_orderkey", F.struct("o_totalprice", -F.col("o_orderkey"))).alias("o_orderkey"))


@case("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    sketch = F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey"))
    return T.load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("hll"), sketch.alias("sketch"))


@case("agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS high FROM events GROUP BY event_type")
def agg_percentile(spark, sf_dir):
    return T.load(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("high"))


# --- windows, sorts, sets ---------------------------------------------------------------------------


@case("win_rank", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY CAST(o_orderdate AS DATE))")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("o_orderpriority").orderBy(F.to_date("o_orderdate"))
    return T.load(spark, sf_dir, "orders").select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"))


@case("win_ntile", "SELECT event_id, ntile(4) OVER (PARTITION BY event_type ORDER BY value, event_id) AS tile FROM events")
def win_ntile(spark, sf_dir):
    return T.load(spark, sf_dir, "events").select("event_id", F.ntile(4).over(Window.partitionBy("event_type").orderBy("value", "event_id")).cast("long").alias("tile"))


@case("win_segments", "SELECT event_id, lead(event_id) OVER w AS next_id, lag(event_id) OVER w AS last_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_segments(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return T.load(spark, sf_dir, "events").select("event_id", F.lead("event_id").over(w).alias("next_id"), F.lag("event_id").over(w).alias("last_id"))


@case("win_positions", "SELECT doc_id, CAST(sum(strlen(text)) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS position FROM documents")
def win_positions(spark, sf_dir):
    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return T.load(spark, sf_dir, "documents").select("doc_id", F.sum(F.octet_length("text").cast("long")).over(w).alias("position"))


@case("win_prefix_boxes", "SELECT event_id, min(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS low, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS rest_high FROM events")
def win_prefix_boxes(spark, sf_dir):
    """The running box from the other end is a running box in reversed order: a frame to the end would be quadratic."""
    ahead = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    behind = Window.partitionBy("user_id").orderBy(F.desc("ts"), F.desc("event_id")).rowsBetween(Window.unboundedPreceding, -1)
    return T.load(spark, sf_dir, "events").select("event_id", F.min("value").over(ahead).alias("low"), F.max("value").over(behind).alias("rest_high"))


@case("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY " + T.days("o_orderdate", "duck", "BIGINT") + " RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS recent FROM orders")
def win_range_frame(spark, sf_dir):
    orders = T.load(spark, sf_dir, "orders").withColumn("day", F.expr(T.days("o_orderdate", "spark", "BIGINT")))
    return orders.select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-90, 0)).alias("recent"))


@case("topk_parts", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY l_partkey ORDER BY n DESC, l_partkey LIMIT 20")
def topk_parts(spark, sf_dir):
    return T.load(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(20)


@case("topk_per_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def topk_per_group(spark, sf_dir):
    order = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return T.load(spark, sf_dir, "orders").withColumn("r", F.row_number().over(order)).where("r <= 2").select("o_custkey", "o_orderkey")


@case("curve_sort", f"SELECT count(*) AS n, 0 AS unsorted FROM ({T.points_sql('lineitem')})")
def curve_sort(spark, sf_dir):
    """Rows sorted by curve key inside each partition; none is out of order."""
    from evenbox.cases.method_cases import _lattice_cells
    from evenbox.functions.curves import z_key

    keyed = _routed(spark, sf_dir).withColumn("key", z_key(_lattice_cells(), 16)).repartition("part_id").sortWithinPartitions("part_id", "key")

    def check(batches):
        last = None
        for rows in batches:
            rows = rows.reset_index(drop=True)
            before = rows.shift(1)
            if last is not None and len(rows):
                before.iloc[0] = last
            bad = ((rows["part_id"] == before["part_id"]) & (rows["key"] < before["key"])).sum()
            last = rows.iloc[-1] if len(rows) else last
            yield pd.DataFrame({"n": [len(rows)], "unsorted": [int(bad)]})

    return keyed.select("part_id", "key").mapInPandas(check, "n long, unsorted long").agg(F.sum("n").alias("n"), F.sum("unsorted").cast("int").alias("unsorted"))


_A, _B = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _keys(spark, sf_dir):
    return T.load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), T.load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))


for _name, _sql, _op in (("union", f"{_A} UNION ALL {_B}", "unionByName"), ("intersect", f"{_A} INTERSECT ALL {_B}", "intersectAll"), ("except", f"{_A} EXCEPT ALL {_B}", "exceptAll"), ("intersect_distinct", f"{_A} INTERSECT {_B}", "intersect"), ("subtract", f"{_A} EXCEPT {_B}", "subtract")):
    case(f"set_{_name}", _sql)(lambda spark, sf_dir, op=_op: getattr(_keys(spark, sf_dir)[0], op)(_keys(spark, sf_dir)[1]))


# --- functions --------------------------------------------------------------------------------------

_HB = f"({T.HOUR_BOXES_SQL})"


@case("fn_box_algebra", f"""SELECT event_type, hour, (x2 - x1) * (y2 - y1) AS area, x2 - x1 + y2 - y1 AS margin, greatest(0, LEAST(x2, 1704200000) - greatest(x1, 1704100000)) * greatest(0, LEAST(y2, 10000) - greatest(y1, 500)) AS shared,
(greatest(x2, 1704200000) - LEAST(x1, 1704100000)) * (greatest(y2, 10000) - LEAST(y1, 500)) - (x2 - x1) * (y2 - y1) AS growth FROM {_HB}""")
def fn_box_algebra(spark, sf_dir):
    lo, hi = geom.cols(("x1", "y1")), geom.cols(("x2", "y2"))
    lo2, hi2 = [F.lit(1704100000), F.lit(500)], [F.lit(1704200000), F.lit(10000)]
    return T.hour_boxes(spark, sf_dir).select("event_type", "hour", geom.volume(lo, hi).alias("area"), geom.margin(lo, hi).alias("margin"), geom.overlap_volume(lo, hi, lo2, hi2).alias("shared"), geom.enlargement(lo, hi, lo2, hi2).alias("growth"))


@case("fn_mindist", f"SELECT event_type, hour, CAST(greatest(x1 - 1704200000, 1704200000 - x2, 0) ** 2 + greatest(y1 - 3000, 3000 - y2, 0) ** 2 AS DOUBLE) AS d2 FROM {_HB}")
def fn_mindist(spark, sf_dir):
    return T.hour_boxes(spark, sf_dir).select("event_type", "hour", geom.gap_squared(geom.cols(("x1", "y1")), geom.cols(("x2", "y2")), [F.lit(1704200000), F.lit(3000)]).alias("d2"))


@case("fn_epoch", f"SELECT event_id, {T.seconds('ts', 'duck', 'BIGINT')} AS s, CAST(date_trunc('hour', ts) AS VARCHAR) AS h FROM events")
def fn_epoch(spark, sf_dir):
    return T.load(spark, sf_dir, "events").selectExpr("event_id", f"{T.seconds('ts', 'spark', 'BIGINT')} AS s", "date_format(date_trunc('HOUR', CAST(ts AS TIMESTAMP)), 'yyyy-MM-dd HH:mm:ss') AS h")


@case("fn_array_box", "SELECT vec_id, list_min(embedding[1:8]) AS low, list_max(embedding[1:8]) AS high, CAST(len(list_filter(embedding, lambda v: v > 0)) AS INTEGER) AS positive FROM embeddings")
def fn_array_box(spark, sf_dir):
    head = F.slice("embedding", 1, 8)
    return T.load(spark, sf_dir, "embeddings").select("vec_id", F.array_min(head).alias("low"), F.array_max(head).alias("high"), F.size(F.filter("embedding", lambda v: v > 0)).alias("positive"))


@case("fn_map_cells", "SELECT l_linenumber, CAST(sum(CASE WHEN l_returnflag = 'A' THEN 1 ELSE 0 END) AS BIGINT) AS a, CAST(sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS BIGINT) AS r FROM lineitem GROUP BY l_linenumber")
def fn_map_cells(spark, sf_dir):
    counts = T.load(spark, sf_dir, "lineitem").groupBy("l_linenumber", "l_returnflag").count()
    maps = counts.groupBy("l_linenumber").agg(F.map_from_entries(F.collect_list(F.struct("l_returnflag", "count"))).alias("m"))
    value = lambda k: F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0)).cast("long")
    return maps.select("l_linenumber", value("A").alias("a"), value("R").alias("r"))


@case("fn_json_props", "SELECT event_id, CAST(length(props) AS INTEGER) AS size, json_valid(props) AS ok FROM events WHERE props IS NOT NULL")
def fn_json_props(spark, sf_dir):
    parsed = F.from_json("props", "map<string,string>")
    return T.load(spark, sf_dir, "events").where("props is not null").select("event_id", F.length("props").alias("size"), parsed.isNotNull().alias("ok"))


@case("udf_box_union", "SELECT o_orderpriority, min(o_totalprice) AS low, max(o_totalprice) AS high FROM orders GROUP BY o_orderpriority")
def udf_box_union(spark, sf_dir):
    def union(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_orderpriority": [rows["o_orderpriority"].iloc[0]], "low": [rows["o_totalprice"].min()], "high": [rows["o_totalprice"].max()]})

    return T.load(spark, sf_dir, "orders").select("o_orderpriority", "o_totalprice").groupBy("o_orderpriority").applyInPandas(union, "o_orderpriority string, low double, high double")


@case("udtf_valid_ranges", VALID_RANGES_SQL.format(queries="SELECT DISTINCT count(*) AS total, 3 AS least, 4 AS most FROM orders GROUP BY o_custkey", columns="total, min(a)::DOUBLE AS low, max(b)::DOUBLE AS high"))
def udtf_valid_ranges(spark, sf_dir):
    """Where the numbers of orders that customers have may be cut into leaves of 3 or 4."""
    @F.udtf(returnType="low double, high double")
    class Ranges:
        def eval(self, total: float, least: float, most: float):
            for a, b in cut_ranges(total, least, most):
                yield float(a), float(b)

    spark.udtf.register("eb_valid_ranges", Ranges)
    totals = T.load(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("total")).select("total").distinct()
    return spark.sql("SELECT total, low, high FROM {totals}, LATERAL eb_valid_ranges(CAST(total AS DOUBLE), 3D, 4D)", totals=totals)


@case("sql_surface", "SELECT l_suppkey, size, (size + 9) // 10 <= size // 9 AS ok FROM (SELECT l_suppkey, count(*) AS size FROM lineitem GROUP BY l_suppkey)")
def sql_surface(spark, sf_dir):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION eb_ok_size(s BIGINT, least BIGINT, most BIGINT) RETURNS BOOLEAN RETURN s > 0 AND floor((s + most - 1) / most) <= floor(s / least)")
    lines = T.load(spark, sf_dir, "lineitem")
    return spark.sql("SELECT l_suppkey, size, eb_ok_size(size, 9, 10) AS ok FROM (SELECT l_suppkey, count(*) AS size FROM {lines} GROUP BY l_suppkey)", lines=lines)


# --- time windows and streams -----------------------------------------------------------------------

@case("win_sliding", f"SELECT event_type, CAST(b * 3600 AS BIGINT) AS s, count(*) AS n FROM (SELECT event_type, unnest([t // 3600, t // 3600 - 1]) AS b FROM (SELECT event_type, {T.seconds('ts', 'duck', 'BIGINT')} AS t FROM events)) GROUP BY ALL")
def win_sliding(spark, sf_dir):
    events = T.load(spark, sf_dir, "events").withColumn("t", F.expr(T.seconds("ts", "spark", "BIGINT")))
    starts = F.explode(F.array(F.floor(F.col("t") / 3600), F.floor(F.col("t") / 3600) - 1))
    return events.select("event_type", starts.alias("b")).groupBy("event_type", (F.col("b") * 3600).alias("s")).agg(F.count("*").alias("n"))


@case("win_session", f"""SELECT user_id, CAST(min(t) AS BIGINT) AS s, count(*) AS n FROM (SELECT user_id, t, sum(new) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT user_id, event_id, t, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) < 7200 THEN 0 ELSE 1 END AS new FROM (SELECT user_id, event_id, {T.seconds('ts', 'duck', 'BIGINT')} AS t FROM events))) GROUP BY user_id, g""")
def win_session(spark, sf_dir):
    events = T.load(spark, sf_dir, "events").select("user_id", F.expr(T.seconds("ts", "spark", "BIGINT")).cast("timestamp").alias("t"))
    # a session window goes on at exactly its gap; times are whole seconds, so a gap of 7200 starts a new one
    return events.groupBy("user_id", F.session_window("t", "7199 seconds").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_seconds("w.start").alias("s"), "n")


def _stream(spark, sf_dir, files: int = 4):
    """The events as a stream of files, in order of time."""
    path = work_path(spark, "stream")
    events = T.load(spark, sf_dir, "events").withColumn("t", F.expr(T.seconds("ts", "spark", "BIGINT")))
    events = events.select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"), F.col("t").cast("double").alias("x"), F.col("value").alias("y"), F.lit(100).cast("long").alias("bytes"), F.expr(f"{T.key_hash('event_id')} AS kh"))
    events.repartitionByRange(files, "ts").write.parquet(f"{path}/in")
    return S.read_files(spark, f"{path}/in", events.schema), f"{path}/checkpoint"


def _name() -> str:
    return f"evenbox_{np.random.default_rng().integers(1 << 60)}"


_EVENTS_CASE = "CASE WHEN (x, y, kh) <= (1705000000.0, 50.0, 0.5) THEN 0 ELSE 1 END"


@case("stream_route", f"SELECT {_EVENTS_CASE} AS part_id, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM ({T.points_sql('events')}) GROUP BY 1")
def stream_route(spark, sf_dir):
    from evenbox.plans.grow import Tree

    stream, checkpoint = _stream(spark, sf_dir)
    routed = S.route_stream(stream, Tree([0], [[1705000000.0, 50.0, 0.5]], [-1], [-2]))
    return S.run_to_table(routed.select("event_id", "part_id"), _name(), checkpoint).groupBy("part_id").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@case("stream_hist_tumbling", f"SELECT CAST(x AS BIGINT) // 86400 * 86400 AS s, CAST(floor(y / 50) AS BIGINT) AS cell, count(*) * 100 AS bytes, count(*) AS n FROM ({T.points_sql('events')}) GROUP BY 1, 2")
def stream_hist_tumbling(spark, sf_dir):
    stream, checkpoint = _stream(spark, sf_dir)
    counted = S.histogram_stream(stream, F.floor(F.col("y") / 50))
    table = S.run_to_table(counted, _name(), checkpoint, "complete")
    return table.select(F.unix_seconds("window.start").alias("s"), "cell", "bytes", "n")


@case("stream_late")
def stream_late(spark, sf_dir):
    """With a short watermark and files out of order, late rows are dropped and the kept ones counted."""
    stream, checkpoint = _stream(spark, sf_dir)
    counted = S.histogram_stream(stream, F.lit(0), "1 day", "1 minute")
    return S.run_to_table(counted, _name(), checkpoint).select(F.unix_seconds("window.start").alias("s"), "n")


@case("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def stream_dedup(spark, sf_dir):
    stream, checkpoint = _stream(spark, sf_dir, 2)
    twice = stream.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    table = S.run_to_table(S.dedup_stream(twice, ["event_id"], "60 days").select("event_id"), _name(), checkpoint)
    return table.agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@case("stream_drift")
def stream_drift(spark, sf_dir):
    from evenbox.plans.grow import Tree

    stream, checkpoint = _stream(spark, sf_dir)
    routed = S.route_stream(stream, Tree([0], [[1705000000.0, 50.0, 0.5]], [-1], [-2])).withColumn("grp", F.lit("all"))
    return S.run_to_table(S.drift_stream(routed.select("grp", "part_id", "bytes")), _name(), checkpoint, "update")


@case("stream_interval_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3600 SECOND")
def stream_interval_join(spark, sf_dir):
    stream, checkpoint = _stream(spark, sf_dir, 1)
    columns = ["user_id", "event_id", "ts"]
    met = S.interval_join_stream(stream.where("event_type = 'click'").select(*columns), stream.where("event_type = 'purchase'").select(*columns), "user_id", 3600)
    return S.run_to_table(met.select(F.col("a.event_id")), _name(), checkpoint).agg(F.count("*").alias("n"))


@case("phase1_once")
def phase1_once(spark, sf_dir):
    """Rows and bytes observed while the sample is taken: one scan for both."""
    from pyspark.sql import Observation

    seen = Observation("phase1")
    df = T.points(spark, sf_dir, "lineitem").observe(seen, F.count("*").alias("n"), F.sum("bytes").alias("b"))
    n = phase1.sample_by_hash(df, 0.05).select("x", "y").toArrow().num_rows
    return spark.createDataFrame([(seen.get["n"], seen.get["b"], n)], "n long, bytes long, sampled long")
