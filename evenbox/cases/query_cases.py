"""Queries for measures, the index and its uses, and the experiment workloads."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from functools import partial, reduce

import pyarrow as pa
from pyspark import StorageLevel, inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.cases.method_cases import FIXED, SHIPMENTS_SQL, _ROUTED, _axes, _routed, shipments
from evenbox.operators import index, phase1, quality, router
from evenbox.operators import spatial_join as sj
from evenbox.operators.learn import learn, runs_of
from evenbox.registry import case
from evenbox.sources import tables as T
from evenbox.sources.io import work_path

Frame = DataFrame
BLOCK = 65536

# --- measures on the manifest of the fixed tree, in cents and days ----------------------------------

_LATTICE = f"SELECT part_id, CAST(round(x * 100) AS BIGINT) AS x, CAST(y AS BIGINT) AS y, bytes FROM ({_ROUTED})"
_MAN = f"SELECT part_id, count(*) AS n_rows, CAST(sum(bytes) AS BIGINT) AS bytes, CAST((sum(bytes) + {BLOCK - 1}) // {BLOCK} AS BIGINT) AS blocks, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y FROM ({_LATTICE}) GROUP BY part_id"
_VOL = "(hi_x - lo_x) * (hi_y - lo_y)"


def _man(spark, sf_dir) -> Frame:
    routed = _routed(spark, sf_dir).selectExpr("part_id", "CAST(round(x * 100) AS BIGINT) AS x", "CAST(y AS BIGINT) AS y", "bytes")
    return quality.manifest(routed, block=BLOCK)


_CELL = "greatest(0, LEAST(a.hi_x, b.hi_x) - greatest(a.lo_x, b.lo_x)) * greatest(0, LEAST(a.hi_y, b.hi_y) - greatest(a.lo_y, b.lo_y))"
_SELF = f"(SELECT coalesce(sum(blocks * (blocks - 1) / 2 * {_VOL}), 0) FROM m)"


def _overlap_sql(times: int) -> str:
    return f"WITH m AS ({_MAN}) SELECT CAST({_SELF} + (SELECT coalesce(sum(a.blocks * b.blocks * {_CELL} * {times}), 0) FROM m a JOIN m b ON a.part_id < b.part_id) AS DOUBLE) AS overlap"


case("metric_volume", f"SELECT CAST(sum(blocks * {_VOL}) AS BIGINT) AS volume FROM ({_MAN})")(lambda spark, sf_dir: quality.total_volume(_man(spark, sf_dir)))
case("metric_margin", f"SELECT CAST(sum(blocks * (hi_x - lo_x + hi_y - lo_y)) AS BIGINT) AS margin FROM ({_MAN})")(lambda spark, sf_dir: quality.total_margin(_man(spark, sf_dir)))
case("metric_overlap", _overlap_sql(1))(lambda spark, sf_dir: quality.total_overlap(_man(spark, sf_dir)).select(F.col("overlap").cast("double")))
case("metric_overlap_ordered", _overlap_sql(2))(lambda spark, sf_dir: quality.total_overlap(_man(spark, sf_dir), ordered=True).select(F.col("overlap").cast("double")))
case("metric_utilisation", f"SELECT round(sum(bytes) / (sum(blocks) * {BLOCK}), 9) AS utilisation FROM ({_MAN})")(lambda spark, sf_dir: quality.utilisation(_man(spark, sf_dir), BLOCK).select(F.round("utilisation", 9).alias("utilisation")))
case("metric_deviation", f"SELECT round(stddev_pop(bytes), 3) AS deviation FROM ({_MAN})")(lambda spark, sf_dir: quality.size_deviation(_man(spark, sf_dir)).select(F.round("deviation", 3).alias("deviation")))
case("metric_load", f"SELECT count(*) AS parts, CAST(sum(blocks) AS BIGINT) AS blocks, min(n_rows) AS min_rows, max(n_rows) AS max_rows, round(min(bytes) / max(bytes), 9) AS fill FROM ({_MAN})")(lambda spark, sf_dir: quality.load_stats(_man(spark, sf_dir)).withColumn("fill", F.round("fill", 9)))
case("needs_rebuild", f"SELECT round(stddev_pop(bytes) / avg(bytes), 6) AS ratio, stddev_pop(bytes) / avg(bytes) > 0.5 AS rebuild FROM ({_MAN})")(lambda spark, sf_dir: quality.needs_rebuild(_man(spark, sf_dir)).withColumn("ratio", F.round("ratio", 6)))


@case("metric_replication", f"SELECT round(count(*) / (SELECT count(*) FROM lineitem), 9) AS replication FROM ({SHIPMENTS_SQL}) JOIN (VALUES (0, '-inf'::DOUBLE, '-inf'::DOUBLE, 50000.0::DOUBLE, 900.0::DOUBLE), (1, '-inf', 900.0, 50000.0, 'inf'), (2, 50000.0, '-inf', 75000.0, 1500.0), (3, 75000.0, '-inf', 'inf', 1500.0), (4, 50000.0, 1500.0, 'inf', 'inf')) r(part_id, rx1, ry1, rx2, ry2) ON x1 <= rx2 AND rx1 <= x2 AND y1 <= ry2 AND ry1 <= y2")
def metric_replication(spark, sf_dir):
    routed = router.route_boxes(shipments(spark, sf_dir), FIXED, sj.LO, sj.HI)
    man = quality.box_manifest(routed, sj.LO, sj.HI)
    return quality.replication(man, T.load(spark, sf_dir, "lineitem").count()).select(F.round("replication", 9).alias("replication"))


_QUERIES = "SELECT CAST(q AS BIGINT) AS qid, 100000 + q % 5 * 2000000 AS qx1, q // 5 * 500 AS qy1, 100000 + q % 5 * 2000000 + 1500000 AS qx2, q // 5 * 500 + 400 AS qy2 FROM range(0, 25) t(q)"
_MEET = "lo_x <= qx2 AND qx1 <= hi_x AND lo_y <= qy2 AND qy1 <= hi_y"
_HELD = "qx1 <= lo_x AND hi_x <= qx2 AND qy1 <= lo_y AND hi_y <= qy2"


def _fixed_queries(spark) -> Frame:
    x, y = F.lit(100000) + F.pmod("id", F.lit(5)) * 2000000, F.floor(F.col("id") / 5) * 500
    return spark.range(25).select(F.col("id").alias("qid"), x.alias("qlo_x"), y.alias("qlo_y"), (x + 1500000).alias("qhi_x"), (y + 400).alias("qhi_y"))


@case("range_blocks", f"SELECT qid, CAST(coalesce(sum(blocks), 0) AS BIGINT) AS blocks, count(part_id) AS parts FROM ({_QUERIES}) LEFT JOIN ({_MAN}) ON {_MEET} GROUP BY qid")
def range_blocks(spark, sf_dir):
    return quality.range_cost(_man(spark, sf_dir), _fixed_queries(spark))


@case("range_blocks_avg", f"SELECT round(avg(blocks), 6) AS blocks FROM (SELECT qid, coalesce(sum(blocks), 0) AS blocks FROM ({_QUERIES}) LEFT JOIN ({_MAN}) ON {_MEET} GROUP BY qid)")
def range_blocks_avg(spark, sf_dir):
    return quality.range_cost(_man(spark, sf_dir), _fixed_queries(spark)).agg(F.round(F.avg("blocks"), 6).alias("blocks"))


@case("range_prune_report", f"SELECT qid, CAST(sum(CASE WHEN {_MEET} THEN 0 ELSE 1 END) AS BIGINT) AS pruned, CAST(sum(CASE WHEN {_HELD} THEN 1 ELSE 0 END) AS BIGINT) AS contained, CAST(sum(CASE WHEN {_MEET} AND NOT ({_HELD}) THEN 1 ELSE 0 END) AS BIGINT) AS boundary FROM ({_QUERIES}), ({_MAN}) GROUP BY qid")
def range_prune_report(spark, sf_dir):
    return quality.prune_report(_man(spark, sf_dir), _fixed_queries(spark))


_MAN2 = _MAN.replace(f"FROM ({_LATTICE})", f"FROM ({_LATTICE} WHERE l_orderkey % 2 = 0)")


@case("join_blocks", f"""WITH a AS ({_MAN}), b AS ({_MAN2}), met AS (SELECT a.part_id AS pa, a.blocks AS ba, b.part_id AS pb, b.blocks AS bb FROM a JOIN b ON a.lo_x <= b.hi_x AND b.lo_x <= a.hi_x AND a.lo_y <= b.hi_y AND b.lo_y <= a.hi_y)
SELECT count(*) AS pairs, CAST(sum(ba * bb) AS BIGINT) AS block_pairs, CAST(sum(ba + bb) AS BIGINT) AS block_reads, CAST((SELECT sum(n) FROM (SELECT DISTINCT pa, ba AS n FROM met)) + (SELECT sum(n) FROM (SELECT DISTINCT pb, bb AS n FROM met)) AS BIGINT) AS distinct_blocks FROM met""")
def join_blocks(spark, sf_dir):
    routed = _routed(spark, sf_dir).where("l_orderkey % 2 = 0").selectExpr("part_id", "CAST(round(x * 100) AS BIGINT) AS x", "CAST(y AS BIGINT) AS y", "bytes")
    return quality.join_cost(_man(spark, sf_dir), quality.manifest(routed, block=BLOCK))


# --- range queries through an index ----------------------------------------------------------------

_PTS = T.points_sql("lineitem")
_BOX = ((20000.0, 400.0), (60000.0, 1300.0))
_IN = "x BETWEEN 20000.0 AND 60000.0 AND y BETWEEN 400.0 AND 1300.0"


def _index(spark, sf_dir, method: str = "mbs_count", name: str = "lineitem", block: int = 1 << 17, ratio: float = 0.1) -> index.Index:
    df = T.points(spark, sf_dir, name)
    return index.write_index(df, learn(df, method, block, ratio=ratio).layout, work_path(spark, "index"), block=block)


@case("index_roundtrip", f"SELECT count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys, CAST(sum(CAST(round(x * 100) AS BIGINT)) AS BIGINT) AS cents FROM ({_PTS})")
def index_roundtrip(spark, sf_dir):
    return _index(spark, sf_dir).data().agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"), F.sum(F.round(F.col("x") * 100).cast("long")).alias("cents"))


@case("range_single", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, x, y FROM ({_PTS}) WHERE {_IN}")
def range_single(spark, sf_dir):
    return _index(spark, sf_dir).range(*_BOX).select(*T.LINE_KEYS, "x", "y")


@case("range_contained_split", f"SELECT count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM ({_PTS}) WHERE {_IN}")
def range_contained_split(spark, sf_dir):
    return _index(spark, sf_dir, "str").range(*_BOX).agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


@case("range_count", f"SELECT count(*) AS n FROM ({_PTS}) WHERE {_IN}")
def range_count(spark, sf_dir):
    return _index(spark, sf_dir, "kd").range_count(*_BOX)


_EDGES = [((1.0, 1.0), (0.0, 0.0)), ((0.0, 0.0), (1e9, 1e9)), ((30000.0, 700.0), (30000.0, 700.0)), ((0.0, 0.0), (50000.0, 900.0))]


@case("range_edge", " UNION ALL ".join(f"SELECT {i} AS qid, count(*) AS n FROM ({_PTS}) WHERE x BETWEEN {a[0]} AND {b[0]} AND y BETWEEN {a[1]} AND {b[1]}" for i, (a, b) in enumerate(_EDGES)))
def range_edge(spark, sf_dir):
    idx, out = _index(spark, sf_dir, "mbs_plain"), None
    for i, (a, b) in enumerate(_EDGES):
        one = idx.range_count(a, b).select(F.lit(i).alias("qid"), "n")
        out = one if out is None else out.unionByName(one)
    return out


_BATCH = "SELECT CAST(q AS BIGINT) AS qid, 1000.0 + q % 5 * 20000 AS qx1, q // 5 * 500.0 AS qy1, 1000.0 + q % 5 * 20000 + 10000 AS qx2, q // 5 * 500.0 + 250 AS qy2 FROM range(0, 25) t(q)"


def _batch(spark) -> Frame:
    x, y = F.lit(1000.0) + F.pmod("id", F.lit(5)) * 20000, F.floor(F.col("id") / 5) * 500.0
    return spark.range(25).select(F.col("id").alias("qid"), x.alias("qlo_x"), y.alias("qlo_y"), (x + 10000).alias("qhi_x"), (y + 250).alias("qhi_y"))


@case("range_batch", f"SELECT qid, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM ({_BATCH}), ({_PTS}) WHERE x BETWEEN qx1 AND qx2 AND y BETWEEN qy1 AND qy2 GROUP BY qid")
def range_batch(spark, sf_dir):
    return _index(spark, sf_dir).range_batch(_batch(spark)).groupBy("qid").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


_TOUCH = "x1 <= 60000.0 AND 20000.0 <= x2 AND y1 <= 1300.0 AND 400.0 <= y2"
_SHIP_SUM = f"SELECT count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM ({SHIPMENTS_SQL}) WHERE {_TOUCH}"


def _summed(df: Frame) -> Frame:
    return df.agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


def _replicated(spark, sf_dir) -> Frame:
    return router.route_boxes(shipments(spark, sf_dir), FIXED, sj.LO, sj.HI)


case("range_boxes", _SHIP_SUM)(lambda spark, sf_dir: _summed(sj.range_boxes(_replicated(spark, sf_dir), FIXED, *_BOX)))
case("dedup_refpoint", _SHIP_SUM)(lambda spark, sf_dir: _summed(sj.range_boxes(_replicated(spark, sf_dir), FIXED, *_BOX).select("l_orderkey")))


@case("dedup_distinct", f"SELECT count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM (SELECT DISTINCT l_orderkey, l_linenumber, l_partkey, l_suppkey, x1, y1 FROM ({SHIPMENTS_SQL}) WHERE {_TOUCH})")
def dedup_distinct(spark, sf_dir):
    return _summed(sj.dedup_distinct(_replicated(spark, sf_dir), [*T.LINE_KEYS, "x1", "y1"], *_BOX))


# --- spatial joins ----------------------------------------------------------------------------------

_SEG, _HOUR = f"({T.SEGMENTS_SQL}) a", f"({T.HOUR_BOXES_SQL}) b"
_ON = {
    "intersects": "a.x1 <= b.x2 AND b.x1 <= a.x2 AND a.y1 <= b.y2 AND b.y1 <= a.y2",
    "contains": "a.x1 <= b.x1 AND b.x2 <= a.x2 AND a.y1 <= b.y1 AND b.y2 <= a.y2",
    "within": "b.x1 <= a.x1 AND a.x2 <= b.x2 AND b.y1 <= a.y1 AND a.y2 <= b.y2",
    "distance": "a.x1 - 600 <= b.x2 AND b.x1 <= a.x2 + 600 AND a.y1 - 600 <= b.y2 AND b.y1 <= a.y2 + 600",
}
_LK, _RK = ("event_id",), ("event_type", "hour")


def _stored(df: Frame, label: str) -> Frame:
    """``df``, computed once: read back from files."""
    path = work_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _sides(spark, sf_dir, method: str = "mbs_count", block: int = 1 << 15) -> tuple[Frame, Frame]:
    """Segments and hour boxes, each in a layout learned from their own centres, routed once and stored."""
    out = []
    for df, key in ((T.segments(spark, sf_dir), "event_id"), (T.hour_boxes(spark, sf_dir), "hour")):
        df = _stored(df.selectExpr("*", "CAST(100 AS BIGINT) AS bytes", f"{T.key_hash(key)} AS kh", "(x1 + x2) / 2 AS x", "(y1 + y2) / 2 AS y"), "boxes")
        out.append(_stored(router.route(df, learn(df, method, block).layout, mode="arrow"), "side"))
    return out[0], out[1]


def _pair_sum(df: Frame) -> Frame:
    return df.groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"), F.sum("hour").alias("hours"))


_PAIR = "SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids, CAST(sum(hour) AS BIGINT) AS hours"


def _join(name: str, kind: str, method: str = "mbs_count", **more) -> None:
    def run(spark, sf_dir):
        left, right = _sides(spark, sf_dir, method)
        return _pair_sum(sj.spatial_join(left, right, kind, 600.0, left_keys=_LK, right_keys=_RK, **more))

    case(name, f"{_PAIR} FROM {_SEG} JOIN {_HOUR} ON {_ON[kind]} GROUP BY event_type")(run)


for _kind in _ON:
    _join(f"join_{_kind}", _kind)
_join("join_intersects_str", "intersects", "str")
_join("join_sweep", "intersects", local="sweep")


@case("join_naive", f"{_PAIR} FROM {_SEG} JOIN {_HOUR} ON {_ON['intersects']} GROUP BY event_type")
def join_naive(spark, sf_dir):
    return _pair_sum(sj.join_broadcast(T.segments(spark, sf_dir), T.hour_boxes(spark, sf_dir), _LK, _RK))


@case("join_copartitioned", f"{_PAIR} FROM {_SEG} JOIN {_HOUR} ON {_ON['intersects']} GROUP BY event_type")
def join_copartitioned(spark, sf_dir):
    left = _stored(T.segments(spark, sf_dir), "segments")
    points = left.selectExpr("(x1 + x2) / 2 AS x", "(y1 + y2) / 2 AS y", "CAST(100 AS BIGINT) AS bytes", f"{T.key_hash('event_id')} AS kh")
    tree = learn(points, "mbs_count", 1 << 15).layout.tree
    return _pair_sum(sj.join_copartitioned(left, _stored(T.hour_boxes(spark, sf_dir), "hours"), tree, _LK, _RK))


for _how, _in in (("left_semi", "IN"), ("left_anti", "NOT IN")):
    case(f"join_{_how[5:]}", f"SELECT event_id FROM {_SEG} WHERE event_id {_in} (SELECT a.event_id FROM {_SEG} JOIN {_HOUR} ON {_ON['within']})")(
        lambda spark, sf_dir, how=_how: sj.spatial_join(*_sides(spark, sf_dir), "within", how=how, left_keys=_LK, right_keys=_RK)
    )


@case("join_left_outer", f"SELECT a.event_id, count(b.hour) AS n FROM {_SEG} LEFT JOIN {_HOUR} ON {_ON['within']} GROUP BY a.event_id")
def join_left_outer(spark, sf_dir):
    return sj.spatial_join(*_sides(spark, sf_dir), "within", how="left", left_keys=_LK, right_keys=_RK).groupBy("event_id").agg(F.count("hour").alias("n"))


@case("join_self_count", f"SELECT count(*) AS n FROM {_HOUR} JOIN ({T.HOUR_BOXES_SQL}) a ON {_ON['intersects']}")
def join_self_count(spark, sf_dir):
    right = _sides(spark, sf_dir)[1]
    twin = right.withColumnsRenamed({"event_type": "type2", "hour": "hour2"})
    return sj.spatial_join(right, twin, left_keys=("event_type",), right_keys=("type2",)).agg(F.count("*").alias("n"))


# --- nearest neighbours and tiles -------------------------------------------------------------------

_ORD = T.points_sql("orders")
_KNN = f"SELECT qid, o_orderkey, rank FROM (SELECT q.o_orderkey AS qid, p.o_orderkey, row_number() OVER (PARTITION BY q.o_orderkey ORDER BY (p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y), p.o_orderkey) AS rank FROM ({_ORD}) q, ({_ORD}) p WHERE q.o_orderkey % {{every}} = 0) WHERE rank <= {{k}}"


def _neighbours(spark, sf_dir, k: int, every: int | None = None) -> Frame:
    """The k orders nearest to each order, or to each whose key ``every`` divides."""
    df = T.points(spark, sf_dir, "orders")
    idx = index.write_index(df, learn(df, "mbs_count", 1 << 14).layout, work_path(spark, "knn"), block=1 << 14)
    asked = (df.where(F.col("o_orderkey") % every == 0) if every else df).select(F.col("o_orderkey").alias("qid"), F.col("x").alias("q_x"), F.col("y").alias("q_y"))
    return idx.knn(asked, k, ["o_orderkey"]).select("qid", "o_orderkey", "rank")


case("knn", _KNN.format(every=100, k=10))(lambda spark, sf_dir: _neighbours(spark, sf_dir, 10, 100))
case("knn_join", _KNN.replace(" WHERE q.o_orderkey % {every} = 0", "").format(k=3))(lambda spark, sf_dir: _neighbours(spark, sf_dir, 3))


@case("tile_pyramid", f"""SELECT zoom, fx >> (6 - zoom) AS tx, fy >> (6 - zoom) AS ty, count(*) AS n, CAST(sum(bytes) AS BIGINT) AS bytes FROM (SELECT bytes, LEAST(63, CAST(floor((x - 0.0) / 110000.0 * 64) AS BIGINT)) AS fx, LEAST(63, CAST(floor((y - 0.0) / 2600.0 * 64) AS BIGINT)) AS fy FROM ({_PTS})), (VALUES (0), (2), (4), (6)) z(zoom) GROUP BY 1, 2, 3""")
def tile_pyramid(spark, sf_dir):
    return sj.tile_counts(T.points(spark, sf_dir, "lineitem"), (0.0, 0.0), (110000.0, 2600.0), (0, 2, 4, 6))


# --- workloads --------------------------------------------------------------------------------------

METHODS = ("mbs_plain", "mbs_count", "mbs_bytes", "str", "kd", "z", "hilbert", "quad", "grid")
#: the balanced variant and the four baselines of the study
STUDY = ("str", "kd", "z", "hilbert")
RESULT = ["workload", "method", "param", "headroom", "parts", "blocks", "volume", "margin", "overlap", "utilisation", "deviation", "seconds", "total_seconds", "blocks_per_query"]


def _unit(df: Frame, axes=("x", "y")) -> Frame:
    """Axes scaled to their extent."""
    ends = phase1.summarize(df, axes).first()
    return df.withColumns({a: (F.col(a) - ends[f"min_{a}"]) / ((ends[f"max_{a}"] - ends[f"min_{a}"]) or 1.0) for a in axes})


def measured(df: Frame, method: str, block: int, workload: str, param: str = "", axes=("x", "y"), queries: Frame | None = None, headroom: float | None = 0.0, scaled: Frame | None = None, **options) -> Callable[[], Frame]:
    """One row, by a function that plans it: all measures of a layout after routing every record, axes scaled to their extent; deviation in blocks.

    seconds: of the boundaries; total_seconds: of all phases, with one scan that routes every record. Every method has the same headroom.
    scaled: ``df`` by ``_unit``, where the caller has it.
    """
    scaled = (_unit(df, axes) if scaled is None else scaled).select(*axes, "bytes", "kh")  # a manifest needs no more
    learned = learn(scaled, method, block, axes, headroom=headroom, **options)
    began = time.perf_counter()
    man = quality.manifest(router.route(scaled, learned.layout, axes, "arrow"), axes, block)
    man = df.sparkSession.createDataFrame(man.toArrow())  # a row for each partition, used by every measure
    total = sum(learned.phases.values()) + time.perf_counter() - began
    asked = queries if queries is not None else index.grid_queries(df.sparkSession, [0.0] * len(axes), [1.0] * len(axes), 100, 0.01, axes)
    labels = {"workload": workload, "method": method, "param": param, "headroom": "default" if headroom is None else f"{headroom:g}", "seconds": learned.seconds, "total_seconds": total}

    def row() -> Frame:
        cost = quality.range_cost(man, asked, axes).agg(F.avg("blocks").alias("blocks_per_query"))
        named = quality.all_measures(man, block, axes).crossJoin(cost).select("*", *[F.lit(v).alias(k) for k, v in labels.items()])
        return named.withColumn("deviation", F.col("deviation") / block).select(*RESULT)

    return row


#: measures that are computed at a time: each is a chain of short jobs over a manifest, which leave the cores idle one by one
AT_ONCE = 6


def _all(rows: list[Callable[[], Frame]]) -> Frame:
    """The rows of all, made now, so that the tables they came from can be let go of."""

    def made_now(row: Callable[[], Frame]) -> tuple[Frame, pa.Table]:
        frame = row()
        return frame, frame.toArrow()  # a row for each layout

    with ThreadPoolExecutor(AT_ONCE) as pool:
        made = list(pool.map(inheritable_thread_target(made_now), rows))
    return made[0][0].sparkSession.createDataFrame(pa.concat_tables([table for _, table in made]), made[0][0].schema)


def _joined(tables: list[Frame]) -> Frame:
    return reduce(DataFrame.unionByName, tables)


@contextmanager
def _kept(df: Frame):
    df = df.cache()
    try:
        yield df
    finally:
        df.unpersist()


@case("ablation_variable_size")
def ablation_variable_size(spark, sf_dir):
    """The three variants and the baselines on records of uneven size, without headroom and with the same for all."""
    out = []
    for table, block in (("documents", 1 << 17), ("pages", 1 << 16)):
        with _kept(T.points(spark, sf_dir, table)) as df:
            out.append(_all([measured(df, m, block, f"ablation_{table}", headroom=h) for h in (0.0, None) for m in ("mbs_plain", "mbs_count", "mbs_bytes", *STUDY)]))
    return _joined(out)


@case("overview_normalised")
def overview_normalised(spark, sf_dir):
    """Every measure over its largest among the methods, without headroom and with the same for all."""
    with _kept(_unit(T.points(spark, sf_dir, "lineitem")).select("x", "y", "bytes", "kh")) as df:
        rows = _all([measured(df, m, 1 << 16, f"overview, headroom {h}", ratio=0.1, headroom=h, scaled=df) for h in (0.0, None) for m in ("mbs_count", *STUDY)])
    return quality.overview(rows, ["volume", "margin", "overlap", "deviation", "utilisation"])


def _sizes(spark, sf_dir, table: str, balanced: str, block: int, ratio: float, shares=(0.25, 0.5, 1.0)) -> Frame:
    with _kept(T.points(spark, sf_dir, table)) as df:
        return _all([measured(phase1.sample_by_hash(df, share, 5), m, block, f"size_{table}", str(share), ratio=ratio) for share in shares for m in (balanced, *STUDY)])


@case("size_sweep_points")
def size_sweep_points(spark, sf_dir):
    return _sizes(spark, sf_dir, "lineitem", "mbs_count", 1 << 16, 0.2)


@case("size_sweep_objects")
def size_sweep_objects(spark, sf_dir):
    return _joined([_sizes(spark, sf_dir, "documents", "mbs_bytes", 1 << 17, 1.0), _sizes(spark, sf_dir, "pages", "mbs_bytes", 1 << 16, 1.0)])


@case("partition_time")
def partition_time(spark, sf_dir):
    """Seconds of every phase and of all, by method: reading the extent, the sample (and histogram), the boundaries, writing the routed records."""
    rows = []
    for table, balanced, block in (("lineitem", "mbs_count", 1 << 16), ("documents", "mbs_bytes", 1 << 17)):
        df = T.points(spark, sf_dir, table)
        for method in (balanced, *STUDY):
            learned = learn(df, method, block, ratio=0.2, headroom=0.0)
            began = time.perf_counter()
            index.write_index(df, learned.layout, work_path(spark, "timed"), block=block)
            phases = learned.phases | {"write": time.perf_counter() - began}
            rows += [(table, method, name, s) for name, s in [*phases.items(), ("total", sum(phases.values()))]]
    return spark.createDataFrame(rows, "data string, method string, phase string, seconds double")


@case("sampling_sweep")
def sampling_sweep(spark, sf_dir):
    """Mean and spread over three samples of each ratio."""
    with _kept(T.points(spark, sf_dir, "documents_hash")) as df:
        rows = _all([measured(df, "mbs_bytes", 1 << 17, "sampling", str(r), ratio=r, seed=s) for r in (0.003, 0.01, 0.03, 0.1, 0.3, 1.0) for s in (1, 2, 3)])
    return quality.repeat_stats(rows, ["workload", "param"], ["volume", "margin", "overlap", "utilisation", "deviation", "seconds"])


@case("rho_sweep")
def rho_sweep(spark, sf_dir):
    with _kept(T.points(spark, sf_dir, "documents_hash")) as df:
        return _all([measured(df, "mbs_bytes", 1 << 17, "rho", str(rho), rho=rho) for rho in (0.0, 0.1, 0.2, 0.3, 0.4, 0.45)])


@case("range_blocks_docs")
def range_blocks_docs(spark, sf_dir):
    """Average blocks of a query on records of uneven size, at three query sizes."""
    with _kept(T.points(spark, sf_dir, "documents_hash")) as df:
        rows = []
        for share in (0.0001, 0.01, 0.1):
            asked = index.grid_queries(spark, [0.0, 0.0], [1.0, 1.0], 200, share)
            rows += [measured(df, m, 1 << 17, "range_docs", str(share), queries=asked) for m in ("mbs_bytes", *STUDY)]
        return _all(rows)


#: the points' extent, and queries of a ten-thousandth of its area
_LOW, _HIGH, _SMALL = (900.0, 0.0), (105000.0, 2600.0), 0.0001
BATCHES = (200, 400, 600, 800, 1000, 1200)


@case("range_batches")
def range_batches(spark, sf_dir):
    """Batches of small boxes on points: blocks to read, records found and seconds, on one index for each method. The index is built before the clock starts."""
    df, rows = T.points(spark, sf_dir, "lineitem"), []
    for method in ("mbs_count", *STUDY):
        idx = index.write_index(df, learn(df, method, 1 << 16, ratio=0.2, headroom=0.0).layout, work_path(spark, "batches"), block=1 << 16)
        for n in BATCHES:
            asked = index.grid_queries(spark, _LOW, _HIGH, n, _SMALL)
            blocks = quality.range_cost(idx.manifest(), asked).agg(F.sum("blocks")).first()[0]
            began = time.perf_counter()
            hits = idx.range_batch(asked).count()
            rows.append((method, n, blocks, hits, time.perf_counter() - began))
    return spark.createDataFrame(rows, "method string, queries int, blocks long, hits long, seconds double")


def _boxes_sql(n: int) -> str:
    """``index.grid_queries`` over the points' extent."""
    side, each = _SMALL**0.5, max(1, int(round(n**0.5)))
    (x0, y0), (x1, y1) = _LOW, _HIGH
    start_x = f"{x0!r} + {(x1 - x0) * (1 - side)!r} * (q % {each} + 0.5) / {max(each, -(-n // each))}"
    start_y = f"{y0!r} + {(y1 - y0) * (1 - side)!r} * (q // {each} + 0.5) / {max(each, -(-n // each))}"
    return f"SELECT CAST(q AS BIGINT) AS qid, {start_x} AS qx, {start_y} AS qy FROM range(0, {n}) t(q)"


@case("range_batch_small", f"SELECT qid, count(*) AS n FROM ({_boxes_sql(1200)}), ({_PTS}) WHERE x BETWEEN qx AND qx + {(_HIGH[0] - _LOW[0]) * _SMALL**0.5!r} AND y BETWEEN qy AND qy + {(_HIGH[1] - _LOW[1]) * _SMALL**0.5!r} GROUP BY qid")
def range_batch_small(spark, sf_dir):
    """The largest of those batches: records in each box."""
    return _index(spark, sf_dir).range_batch(index.grid_queries(spark, _LOW, _HIGH, 1200, _SMALL)).groupBy("qid").agg(F.count("*").alias("n"))


def _dimensions(spark, name: str, tables: list[tuple[int, Frame]], block: int, ratio: float) -> Frame:
    out = []
    for d, table in tables:
        with _kept(_unit(table, _axes(d)).select(*_axes(d), "bytes", "kh")) as df:
            out.append(_all([measured(df, m, block, name, str(d), _axes(d), ratio=ratio, scaled=df) for m in ("mbs_count", *STUDY)]))
    return _joined(out)


@case("multidim_diagonal")
def multidim_diagonal(spark, sf_dir):
    return _dimensions(spark, "diagonal", [(d, T.diagonal(spark, sf_dir, d)) for d in (3, 4, 5, 9)], 1 << 18, 0.1)


@case("multidim_trips")
def multidim_trips(spark, sf_dir):
    return _dimensions(spark, "trips", [(d, T.trips(spark, sf_dir, d)) for d in (4, 5, 7)], 1 << 18, 0.1)


@case("multidim_vectors")
def multidim_vectors(spark, sf_dir):
    return _dimensions(spark, "vectors", [(d, T.vectors(spark, sf_dir, d)) for d in (4, 5, 7, 9)], 1 << 12, 1.0)


def _boxed(df: Frame, *keys: str) -> Frame:
    """Boxes with the columns that layouts are learned from: their centres."""
    return df.selectExpr("*", f"{T.key_hash(*keys)} AS kh", "(x1 + x2) / 2 AS x", "(y1 + y2) / 2 AS y")


def _join_cost(left: Frame, right: Frame, labels: dict) -> Frame:
    return quality.join_cost(left, right).select(*[F.lit(v).alias(k) for k, v in labels.items()], "*")


@case("join_cost_methods")
def join_cost_methods(spark, sf_dir):
    """Blocks a spatial join reads, by method: two pairs of data, each joined small and large against small and large."""
    orders = T.load(spark, sf_dir, "orders").selectExpr("o_orderkey", "o_totalprice AS x1", f"{T.days('o_orderdate', 'spark')} AS y1", "o_totalprice * 1.05 AS x2", f"{T.days('o_orderdate', 'spark')} + 30 AS y2", "CAST(100 AS BIGINT) AS bytes")
    ships = shipments(spark, sf_dir).drop("kh")
    hours = T.hour_boxes(spark, sf_dir).selectExpr("*", "CAST(100 AS BIGINT) AS bytes")
    lines = T.segments(spark, sf_dir).selectExpr("*", "CAST(100 AS BIGINT) AS bytes")
    pairs = (("hour boxes x segments", _boxed(hours, "hour"), _boxed(lines, "event_id"), 1 << 14), ("order boxes x shipments", _boxed(orders, "o_orderkey"), _boxed(ships, *T.LINE_KEYS), 1 << 17))
    rows = []
    for name, left, right, block in pairs:
        for method in ("mbs_count", "mbs_plain", *STUDY):
            sides = [{}, {}]
            for side, df in zip(sides, (left, right), strict=True):
                for share in (0.5, 1.0):
                    part = df if share == 1.0 else phase1.sample_by_hash(df, share, 5)
                    routed = router.route(part, learn(part, method, block, headroom=0.0).layout)
                    man = quality.with_blocks(quality.box_manifest(routed, sj.LO, sj.HI), block)
                    side[share] = spark.createDataFrame(man.toArrow())  # a row for each partition
            for a in (0.5, 1.0):
                for b in (0.5, 1.0):
                    rows.append(partial(_join_cost, sides[0][a], sides[1][b], {"data": name, "method": method, "left_share": a, "right_share": b}))
    return _all(rows)


@case("scale_up")
def scale_up(spark, sf_dir):
    """Partitioning shares of the table at three widths of the shuffle: records, partitions and seconds of learning and of routing with the
    shuffle. What is routed does not depend on the width, so each share is routed once, and those seconds count at every width."""
    rows = []
    for share in (0.25, 0.5, 1.0):
        df = phase1.sample_by_hash(T.points(spark, sf_dir, "lineitem"), share, 5)
        learned = learn(df, "mbs_count", 1 << 17, ratio=0.1)
        began = time.perf_counter()
        routed = router.route(df.select("x", "y", "kh"), learned.layout, mode="arrow").select("part_id").persist(StorageLevel.DISK_ONLY)
        routed.count()
        routing = time.perf_counter() - began
        for width in (1, 4, 8):
            began = time.perf_counter()
            done = routed.repartition(width, "part_id").groupBy("part_id").count().agg(F.count("*"), F.sum("count")).first()
            rows.append((share, width, done[0], done[1], sum(learned.phases.values()), routing + time.perf_counter() - began))
        routed.unpersist()
    return spark.createDataFrame(rows, "share double, width int, parts long, n long, learn_seconds double, route_seconds double")


#: the places that need no learning, against which layouts are held
CONTROLS = ("hash", "round_robin", "range", "grid")


@case("control_layouts")
def control_layouts(spark, sf_dir):
    """Measures of records dealt by key hash, in turn, by ranges of one axis and by a grid, beside the balanced layout."""
    block, rows = 1 << 16, []
    with _kept(_unit(T.points(spark, sf_dir, "lineitem")).select("x", "y", "bytes", "kh")) as df:
        data = df.agg(F.sum("bytes")).first()[0]
        n = max(1, -(-data // block))
        dealt = {
            "hash": df.withColumn("part_id", F.floor(F.col("kh") * n).cast("int") if dict(df.dtypes)["kh"] == "double" else F.pmod("kh", F.lit(n)).cast("int")),
            # in turn within each task, without a task for each partition
            "round_robin": df.withColumn("part_id", F.pmod(F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1) + F.spark_partition_id() * 7919, F.lit(n)).cast("int")),
            "range": router.route_points(df, runs_of(phase1.sample_by_hash(df, 0.2), n), mode="arrow"),
        }
        for method in (*CONTROLS, "mbs_count"):
            routed = dealt[method] if method in dealt else router.route(df, learn(df, method, block, ratio=0.2, headroom=0.0).layout, mode="arrow")
            man = spark.createDataFrame(quality.manifest(routed, block=block).toArrow())  # a row for each partition
            rows.append(lambda man=man, method=method: quality.all_measures(man, block).select(F.lit(method).alias("method"), "*"))
        return _all(rows)
