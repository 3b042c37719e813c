"""Queries against their SQL, and layouts against brute force, on the smallest tables."""

import threading
from datetime import datetime, timedelta
from functools import partial

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql.streaming.readwriter import DataStreamWriter

from evenbox import registry, workloads
from evenbox.cases import query_cases
from evenbox.operators import index, learn, phase1, quality, router
from evenbox.operators import spatial_join as sj
from evenbox.operators.meeting import CellGrid, meeting
from evenbox.plans import baselines
from evenbox.plans.baselines import curve_runs
from evenbox.plans.cut import Spec
from evenbox.plans.grow import grow
from evenbox.sources import tables as T

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PICKED = ["size_validity_grid", "witness_sizes", "valid_ranges", "extent_lineitem", "byte_histogram_docs", "point_weights_docs", "weight_totals", "first_cut_rho", "route_points_tree", "route_points_case", "route_points_arrow", "route_boxes_tree", "route_min_area", "str_2d", "kd_8", "z_partitions", "hilbert_keys", "metric_overlap", "range_single", "range_batch", "range_boxes", "join_intersects", "join_sweep", "join_copartitioned", "knn", "tile_pyramid", "join_asof", "win_prefix_boxes", "stream_route"]


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def rounded(value):
    if isinstance(value, float):
        return float(f"{value:.9g}")
    return value


@pytest.mark.parametrize("name", PICKED)
def test_against_sql(spark, small, duck, name):
    frame = workloads.queries()[name](spark, small)
    columns = sorted(frame.columns)
    got = sorted(repr(tuple(rounded(r[c]) for c in columns)) for r in frame.collect())
    found = duck.execute(registry.SQL[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == columns
    want = sorted(repr(tuple(rounded(dict(zip(names, r, strict=True))[c]) for c in columns)) for r in found.fetchall())
    assert got == want


def test_knn_asks_for_every_100th_order(spark, small):
    points = [(r["o_orderkey"], r["x"], r["y"]) for r in T.points(spark, small, "orders").select("o_orderkey", "x", "y").collect()]
    want = {(q, p[0], rank) for q, x, y in points if q % 100 == 0 for rank, p in enumerate(sorted(points, key=lambda p: ((p[1] - x) ** 2 + (p[2] - y) ** 2, p[0]))[:10], 1)}
    got = {(r["qid"], r["o_orderkey"], r["rank"]) for r in workloads.queries()["knn_every_100"](spark, small).collect()}
    assert got == want and len(want) == 10 * sum(q % 100 == 0 for q, *_ in points)


def test_lateral_topk_serves_every_customer(spark, small, duck):
    got = sorted((r["c_custkey"], r["o_orderkey"]) for r in workloads.queries()["join_lateral_topk_all"](spark, small).collect())
    assert got == sorted(duck.execute(registry.SQL["join_lateral_topk_all"]).fetchall())
    assert len({c for c, _ in got}) == duck.execute("SELECT count(DISTINCT o_custkey) FROM orders JOIN customer ON o_custkey = c_custkey").fetchone()[0]


@pytest.mark.parametrize("method", learn.METHODS)
def test_every_method_places_every_record(spark, small, method):
    df = T.points(spark, small, "documents_hash")
    layout = learn.learn(df, method, 1 << 15).layout
    man = quality.manifest(router.route(df, layout), block=1 << 15)
    assert man.agg({"n_rows": "sum"}).first()[0] == df.count()


def test_bytes_variant_has_the_least_deviation(spark, small):
    df = T.points(spark, small, "documents_hash")
    sizes = {m: quality.size_deviation(quality.manifest(router.route(df, learn.learn(df, m, 1 << 15).layout))).first()[0] for m in ("mbs_bytes", "mbs_count", "str", "kd")}
    assert sizes["mbs_bytes"] == min(sizes.values())


def test_routers_agree_with_numpy(spark):
    random = np.random.default_rng(0)
    points, hashes = np.round(random.random((500, 2)), 1), random.random(500)
    tree = grow(points, hashes, Spec("count", 19, 21)).tree
    df = spark.createDataFrame([(float(x), float(y), float(h)) for (x, y), h in zip(points, hashes, strict=True)], "x double, y double, kh double")
    want = tree.route(points, hashes).tolist()
    for mode in ("tree", "case", "arrow"):
        assert [r["part_id"] for r in router.route_points(df, tree, mode=mode).collect()] == want


def test_empty_table(spark, small, tmp_path):
    df = T.points(spark, small, "orders").where("false")
    layout = learn.learn(df, "mbs_count", 1 << 15).layout
    idx = index.write_index(df, layout, f"{tmp_path}/empty")
    assert idx.manifest().count() == 0 and phase1.summarize(df).first()["n_rows"] == 0


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["layout_mbs_d5", "layout_mbs_d7", "layout_mbs_d9"])
def test_large_samples_grow_in_tasks(spark, small, monkeypatch, name):
    """What the driver takes in is a thin sample; the leaves still hold every point of the full one."""
    d = int(name[-1])
    df = (T.diagonal if d == 9 else T.trips)(spark, small, d)
    whole = phase1.sample_by_hash(df, 0.1).count()
    monkeypatch.setattr(learn, "DRIVER_VALUES", 50 * (d + 1))
    monkeypatch.setattr(learn, "TASK_VALUES", 100 * (d + 1))
    monkeypatch.setattr(learn, "TOP_VALUES", 60 * (d + 1))
    taken, inner = [], phase1.to_numpy
    monkeypatch.setattr(phase1, "to_numpy", lambda *a, **k: taken.append(len((out := inner(*a, **k))[0])) or out)
    rows = workloads.queries()[name](spark, small).collect()
    assert sum(r["n"] for r in rows) == whole and max(taken) < whole / 4


def test_first_levels_of_a_tenth_come_from_a_thin_sample_of_it(spark, monkeypatch):
    """Another turn of the key hash had no row in common with the tenth, so one task grew all of it."""
    df = spark.range(20000).selectExpr("CAST(id * 7919 % 10007 AS DOUBLE) AS x", "CAST(id * 104729 % 10009 AS DOUBLE) AS y", "100L AS bytes", "CAST(id * 48271 % 1000003 AS DOUBLE) / 1000003 AS kh")
    tops, inner = [], learn.grow_top
    monkeypatch.setattr(learn, "grow_top", lambda *a: tops.append(inner(*a)) or tops[-1])
    layout = learn.learn_distributed(df, 1 << 13, ratio=0.1, task_points=200, top_points=40).layout
    assert len(tops) == 1 and tops[0].parts >= 5 and layout.parts > tops[0].parts
    assert sum(layout.counts.values()) == phase1.sample_by_hash(df, 0.1).count()


def test_filters_on_the_diagonal_do_not_make_its_axes_again(spark, small, duck):
    """Eighteen copies of the axes' expressions in one filter were too long to be compiled."""
    axes = [f"a{i}" for i in range(9)]
    df = T.diagonal(spark, small, 9)
    plan = df.where(phase1.valid(axes))._jdf.queryExecution().optimizedPlan().toString()
    assert not [line for line in plan.splitlines() if "Filter" in line and "CASE" in line]
    want = duck.sql(f"SELECT {', '.join(T.LINE_KEYS)}, {', '.join(f'CAST({x} AS DOUBLE)' for x in T.diagonal_sql(9))}, {T.key_hash(*T.LINE_KEYS)} FROM lineitem").fetchall()
    assert sorted(want) == sorted(tuple(r) for r in df.drop("bytes").collect())


def test_scale_up_routes_each_share_once(spark, small, monkeypatch):
    """Three widths of the shuffle have the same routed records, and all of them."""
    calls, inner = [], router.route
    monkeypatch.setattr(router, "route", lambda *a, **k: calls.append(a) or inner(*a, **k))
    rows = workloads.queries()["scale_up"](spark, small).collect()
    points = T.points(spark, small, "lineitem")
    assert [(r["share"], r["width"], r["n"]) for r in rows] == [(s, w, phase1.sample_by_hash(points, s, 5).count()) for s in (0.25, 0.5, 1.0) for w in (1, 4, 8)]
    assert len(calls) == 3 and all(r["route_seconds"] > 0 for r in rows) and len({(r["share"], r["parts"]) for r in rows}) == 3


def test_appended_rows_of_a_stream_are_files(spark, small, duck, monkeypatch):
    """The memory sink holds every row on the driver; only results with a row for each group may use it."""
    kinds, inner = [], DataStreamWriter.format
    monkeypatch.setattr(DataStreamWriter, "format", lambda self, kind: kinds.append(kind) or inner(self, kind))
    for name in ("stream_dedup", "stream_route"):
        found = duck.execute(registry.SQL[name])
        names = [d[0] for d in found.description]
        assert sorted(tuple(r[n] for n in names) for r in workloads.queries()[name](spark, small).collect()) == sorted(found.fetchall())
    assert kinds and "memory" not in kinds


def _events(tmp_path, rows):
    table = pa.table({"event_id": pa.array(range(len(rows)), pa.int64()), "ts": pa.array([t for t, _ in rows], pa.timestamp("us")), "user_id": pa.array([1] * len(rows), pa.int64()), "event_type": [k for _, k in rows], "value": [1.0] * len(rows), "props": ["{}"] * len(rows)})
    pq.write_table(table, f"{tmp_path}/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet'")
    return con


def test_a_gap_of_exactly_the_session_time_ends_it(spark, tmp_path):
    at = lambda s: datetime(2024, 1, 1) + timedelta(seconds=s)
    con = _events(tmp_path, [(at(s), "click") for s in (0, 7199, 14399, 14400)])
    got = sorted((r["user_id"], r["s"], r["n"]) for r in workloads.queries()["win_session"](spark, str(tmp_path)).collect())
    assert got == sorted(con.execute(registry.SQL["win_session"]).fetchall()) and len(got) == 2


def test_stream_join_keeps_parts_of_a_second(spark, tmp_path):
    at = lambda s: datetime(2024, 1, 1) + timedelta(seconds=s)
    con = _events(tmp_path, [(at(10.5), "click"), (at(10.25), "purchase"), (at(10.75), "purchase"), (at(3610.5), "purchase"), (at(3610.6), "purchase")])
    got = workloads.queries()["stream_interval_join"](spark, str(tmp_path)).first()["n"]
    assert got == con.execute(registry.SQL["stream_interval_join"]).fetchone()[0] == 2


def test_small_partitions_share_folders(spark, small, tmp_path):
    """Tasks and files of an index follow its bytes, not the number of its partitions; queries still find their records by partition."""
    df = T.points(spark, small, "lineitem")
    idx = index.write_index(df, learn.learn(df, "mbs_count", 1 << 12).layout, f"{tmp_path}/many", block=1 << 12)
    assert idx.manifest().count() > 100 and len(list((tmp_path / "many" / "data").rglob("*.parquet"))) == 1
    lo, hi = (20000.0, 400.0), (60000.0, 1300.0)
    want = df.where("x BETWEEN 20000 AND 60000 AND y BETWEEN 400 AND 1300").count()
    assert idx.range(lo, hi).count() == idx.range_count(lo, hi).first()["n"] == want > 0
    assert idx.data().columns == [*df.columns, "part_id"] and index.Index(spark, f"{tmp_path}/many").range(lo, hi).count() == want


@pytest.mark.parametrize("name", ["hilbert_pack", "z_partitions"])
def test_curve_cuts_of_a_whole_table_need_no_points_on_the_driver(spark, small, monkeypatch, name):
    points = phase1.to_numpy(T.points(spark, small, "events"), ("x", "y"))[0]
    method = name.split("_")[0]
    for parts in (1, 7, 20, 2000):
        assert learn.curve_runs_of(T.points(spark, small, "events"), parts, method, 10).cuts == curve_runs(points, parts, method, 10).cuts
    monkeypatch.setattr(phase1, "DRIVER_POINTS", 100)
    assert workloads.queries()[name](spark, small).agg({"n": "sum"}).first()[0] == len(points)


TABLED = ["capacity_grid", "kd_depth", "regions_cover", "sample_need_grid", "size_validity_grid", "sql_surface", "str_fanout", "threshold_grid", "udtf_valid_ranges"]


@pytest.mark.parametrize("name", [*TABLED, "capacity_spec", "source_diagonal"])
def test_sizes_come_from_a_given_table(spark, small, duck, monkeypatch, name):
    """Each reads a table with Spark, and gives what its SQL gives on it."""
    read, inner = [], T.load
    monkeypatch.setattr(T, "load", lambda spark, sf_dir, table: read.append(table) or inner(spark, sf_dir, table))
    frame = workloads.queries()[name](spark, small)
    assert read and frame.count()
    if name in TABLED:
        test_against_sql(spark, small, duck, name)
    if name == "source_diagonal":
        assert frame.count() == inner(spark, small, "orders").count()


@pytest.mark.parametrize("name", ["knn", "knn_join"])
def test_neighbours_of_more_points_than_the_driver_takes(spark, small, duck, monkeypatch, name):
    monkeypatch.setattr(phase1, "DRIVER_POINTS", 1000)
    for limit, points in (("DRIVER_VALUES", 1000), ("TASK_VALUES", 300), ("TOP_VALUES", 300)):
        monkeypatch.setattr(learn, limit, points * 3)
    test_against_sql(spark, small, duck, name)


def test_knn_join_asks_for_every_order(spark, small, duck):
    """No order is left out, neither by the query nor by its SQL."""
    got = sorted((r["qid"], r["o_orderkey"], r["rank"]) for r in workloads.queries()["knn_join"](spark, small).collect())
    assert len({q for q, *_ in got}) == T.load(spark, small, "orders").count()
    assert got == sorted(duck.execute(registry.SQL["knn_join"]).fetchall())


@pytest.mark.parametrize("d", [2, 5])
@pytest.mark.parametrize("method", learn.BASELINES)
def test_baselines_of_many_points_are_cut_on_the_executors(spark, small, monkeypatch, method, d):
    """The same layout as on the driver, which takes no points."""
    df, axes = (T.points(spark, small, "lineitem"), ["x", "y"]) if d == 2 else (T.trips(spark, small, d), [f"a{i}" for i in range(d)])
    want = learn.learn(df, method, 1 << 15, axes, ratio=0.5).layout
    monkeypatch.setattr(learn, "DRIVER_VALUES", 1000)
    monkeypatch.setattr(learn, "SHARE_VALUES", 600 * (d + 1))
    monkeypatch.setattr(phase1, "to_numpy", None)
    got = learn.learn(df, method, 1 << 15, axes, ratio=0.5).layout
    assert got.parts == want.parts > 10 and got.extent(d) == want.extent(d)
    if method in ("z", "hilbert"):
        assert got.cuts == want.cuts
    else:
        assert (got.tree, got.boxes, got.counts) == (want.tree, want.boxes, want.counts)


@pytest.mark.parametrize("name", ["multidim_diagonal", "multidim_trips"])
def test_dimensions_need_no_points_on_the_driver(spark, small, monkeypatch, name):
    """Measures do not depend on where the boundaries are made."""
    monkeypatch.setattr(query_cases, "STUDY", ("str", "kd", "z"))
    tables = {"multidim_diagonal": (3, T.diagonal), "multidim_trips": (7, T.trips)}[name]
    rows = lambda: [r.asDict() for r in query_cases._dimensions(spark, name, [(tables[0], tables[1](spark, small, tables[0]))], 1 << 15, 0.5).collect()]
    want = {r["method"]: r for r in rows()}
    monkeypatch.setattr(learn, "DRIVER_VALUES", 1000)
    monkeypatch.setattr(phase1, "DRIVER_POINTS", 2000)  # the sample has some 3,000
    for row in rows():
        if row["method"] != "mbs_count":  # its first levels are grown from a thin sample
            assert {k: v for k, v in row.items() if "seconds" not in k} == pytest.approx({k: v for k, v in want[row["method"]].items() if "seconds" not in k})


@pytest.mark.parametrize("d", [2, 5])
def test_overlap_of_crowded_cells(spark, monkeypatch, d):
    """Many boxes in one cell: their pairs are made in blocks, each once."""
    random = np.random.default_rng(3)
    low = random.random((300, d))
    high, blocks = np.minimum(1, low + random.random((300, d)) * 0.4), random.integers(1, 4, 300)
    low[:100], high[:100] = 0, 1
    axes = list("xyzuv")[:d]
    man = spark.createDataFrame([(i, int(blocks[i]), *low[i].tolist(), *high[i].tolist()) for i in range(300)], f"part_id int, blocks long, {', '.join(f'lo_{a} double' for a in axes)}, {', '.join(f'hi_{a} double' for a in axes)}")
    want = sum(blocks[i] * (blocks[i] - 1) / 2 * np.prod(high[i] - low[i]) for i in range(300))
    want += sum((blocks[i] * blocks[i + 1 :] * np.maximum(np.minimum(high[i], high[i + 1 :]) - np.maximum(low[i], low[i + 1 :]), 0).prod(axis=1)).sum() for i in range(299))
    for crowded in (40, 10_000):
        monkeypatch.setattr(quality, "CROWDED", crowded)
        assert quality.total_overlap(man, axes).first()[0] == pytest.approx(want)
        assert quality.total_overlap(man, axes, ordered=True).first()[0] > want


def test_controls_need_no_points_on_the_driver(spark, small, monkeypatch):
    """Ranges and the grid are cut on the executors too, and lie where they did."""
    sample = phase1.sample_by_hash(T.points(spark, small, "lineitem"), 0.2)
    assert learn.runs_of(sample, 10) == baselines.runs(*phase1.to_numpy(sample, ("x", "y"))[:2], 10).tree
    want = {r["method"]: r for r in workloads.queries()["control_layouts"](spark, small).collect()}
    monkeypatch.setattr(learn, "DRIVER_VALUES", 1000)
    monkeypatch.setattr(phase1, "DRIVER_POINTS", 1000)  # the sample has some 1,200
    got = {r["method"]: r for r in workloads.queries()["control_layouts"](spark, small).collect()}
    for method in ("hash", "range", "grid"):
        assert got[method].asDict() == pytest.approx(want[method].asDict())


def test_boxes_that_cover_an_axis_get_few_cells(spark):
    """Partitions dealt by hash all cover the whole extent; they meet in one cell, not in every one."""
    boxes = spark.createDataFrame([(i, 0.0, 0.0, 0.0, 1.0, 1.0, i + 1.0) for i in range(400)], "part_id int, lo_x double, lo_y double, lo_z double, hi_x double, hi_y double, hi_z double")
    grid = CellGrid(boxes, ["lo_x", "lo_y"], ["hi_x", "hi_y"])
    assert grid.dealt(boxes, ["lo_x", "lo_y"], ["hi_x", "hi_y"], "a").count() == 400
    other = boxes.toDF("part_b", *[f"{c}_b" for c in boxes.columns[1:]])
    sides = []
    for end in ("", "_b"):
        sides.append(([f"lo_{a}{end}" for a in "xyz"], [f"hi_{a}{end}" for a in "xyz"]))
    assert meeting(boxes, other, *sides).count() == 400 * 400


def test_controls_place_every_record(spark, small):
    rows = {r["method"]: r for r in workloads.queries()["control_layouts"](spark, small).collect()}
    assert set(rows) == {"hash", "round_robin", "range", "grid", "mbs_count"}
    assert rows["round_robin"]["deviation"] < 0.05 * (1 << 16) and rows["range"]["parts"] == rows["hash"]["parts"] == 10


def test_join_routes_no_more_copies_than_boxes_need(spark, small, monkeypatch):
    """Wide boxes over a tree of many narrow regions: copies grow with the boxes, not with the regions that they cover."""
    left, right = T.segments(spark, small), T.hour_boxes(spark, small)
    points = left.selectExpr("(x1 + x2) / 2 AS x", "(y1 + y2) / 2 AS y", "CAST(100 AS BIGINT) AS bytes", f"{T.key_hash('event_id')} AS kh")
    tree = learn.learn(points, "mbs_count", 1 << 9).layout.tree
    made, inner = [], sj.route_boxes
    monkeypatch.setattr(sj, "route_boxes", lambda df, *a, **k: made.append((df, inner(df, *a, **k))) or made[-1][1])
    got = sorted(map(tuple, sj.join_copartitioned(left, right, tree, ("event_id",), ("event_type", "hour")).collect()))
    assert len(tree.axis) > 150 and all(copies.count() <= 6 * df.count() for df, copies in made)
    assert got == sorted(map(tuple, sj.join_broadcast(left, right, ("event_id",), ("event_type", "hour")).collect()))


def test_boxes_are_routed_alike_by_arrow(spark):
    random = np.random.default_rng(1)
    points = np.round(random.random((400, 2)), 1)
    tree = grow(points, random.random(400), Spec("count", 19, 21)).tree
    df = spark.createDataFrame([(i, *p.tolist(), *(p + 0.25).tolist()) for i, p in enumerate(points)], "id long, x1 double, y1 double, x2 double, y2 double")
    by = [sorted((r["id"], r["part_id"]) for r in router.route_boxes(df, tree, ("x1", "y1"), ("x2", "y2"), mode).collect()) for mode in ("tree", "arrow")]
    assert by[0] == by[1] and len(by[0]) > 400


@pytest.mark.parametrize(("kind", "side"), [("within", "a"), ("contains", "b")])
def test_records_go_only_where_a_box_can_hold_them(spark, small, monkeypatch, kind, side):
    """A record that another has to hold is looked for in the partitions that hold it, in one cell of each."""
    big = T.segments(spark, small)
    df = {"a": T.hour_boxes(spark, small), "b": T.hour_boxes(spark, small)} | {side: big}
    sides = [df[s].selectExpr("*", "CAST(100 AS BIGINT) AS bytes", f"CAST({k} % 7 AS INT) AS part_id") for s, k in (("a", "event_id" if side == "a" else "hour"), ("b", "event_id" if side == "b" else "hour"))]
    keys = [("event_id",) if s == side else ("event_type", "hour") for s in "ab"]
    dealt, inner = [], CellGrid.placed
    monkeypatch.setattr(CellGrid, "placed", lambda self, boxes, lo, tag: dealt.append((tag, boxes)) or inner(self, boxes, lo, tag))
    got = sorted(map(tuple, sj.spatial_join(*sides, kind, left_keys=keys[0], right_keys=keys[1]).collect()))
    assert got == sorted(map(tuple, sj.join_broadcast(*sides, keys[0], keys[1], kind).collect())) and got
    assert [tag for tag, _ in dealt] == [side] and dealt[0][1].count() <= 7 * big.count()


def test_medians_sort_only_points_that_tie(monkeypatch):
    """Half of a node's points is found by selection: the cuts are those of the whole order, without ordering all points at each level."""
    random = np.random.default_rng(2)
    points, hashes = np.column_stack([random.random(4000), np.floor(random.random(4000) * 500)]), random.random(4000)
    sorted_points, inner = [], baselines.axis_order
    monkeypatch.setattr(baselines, "axis_order", lambda p, h, a: sorted_points.append(len(p)) or inner(p, h, a))
    layout = baselines.medians(points, hashes, 64)
    first = inner(points, hashes, 0)[1999]
    assert layout.tree.cut[0] == [*points[first], hashes[first]] and set(layout.counts.values()) == {62, 63}
    assert sum(sorted_points) < len(points)


def test_few_pairs_of_queries_and_partitions_are_sent_to_the_records(spark, small, tmp_path):
    """A batch does not shuffle the stored records, whatever Spark's own limit of a broadcast is; beyond SENT_PAIRS it may."""
    df = T.points(spark, small, "lineitem")
    idx = index.write_index(df, learn.learn(df, "mbs_count", 1 << 14).layout, f"{tmp_path}/batch", block=1 << 14)
    asked = index.grid_queries(spark, (900.0, 0.0), (105000.0, 2600.0), 100, 0.001)
    limit = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        batch = idx.range_batch(asked)
        plan, n = batch._jdf.queryExecution().executedPlan().toString(), batch.count()
        index.SENT_PAIRS, most = 0, index.SENT_PAIRS
        assert idx.range_batch(asked).count() == n > 0
        index.SENT_PAIRS = most
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    assert "BroadcastHashJoin" in plan


def test_a_sample_of_one_task_grows_there(spark, small, monkeypatch):
    """Too much for the driver, but no more than one task takes: there are no first levels."""
    df = T.points(spark, small, "lineitem")
    want = learn.learn(df, "mbs_count", 1 << 14).layout
    monkeypatch.setattr(learn, "DRIVER_VALUES", 1000)
    got = learn.learn(df, "mbs_count", 1 << 14).layout
    assert got.boxes == want.boxes and got.counters == want.counters


def test_measures_of_layouts_are_computed_side_by_side(spark, monkeypatch):
    """Chains of short jobs overlap; rows keep their order."""
    waiting = threading.Barrier(3, timeout=60)

    def row(i):
        waiting.wait()  # passes only if three are under way
        return spark.range(1).selectExpr(f"{i} AS i")

    assert [r["i"] for r in query_cases._all([partial(row, i) for i in range(3)]).collect()] == [0, 1, 2]


@pytest.mark.parametrize("method", ["z", "hilbert"])
def test_many_curve_cuts_are_not_compared_one_by_one(spark, small, monkeypatch, method):
    df = T.points(spark, small, "lineitem")
    layout = learn.learn(df, method, 1 << 12).layout
    routed = router.route(df, layout)
    assert len(layout.cuts) > router.CURVE_CUTS and "filter(" not in routed._jdf.queryExecution().optimizedPlan().toString()
    got = sorted((*(r[k] for k in T.LINE_KEYS), r["part_id"]) for r in routed.collect())
    monkeypatch.setattr(router, "CURVE_CUTS", len(layout.cuts))
    plain = router.route(df, layout)
    assert got == sorted((*(r[k] for k in T.LINE_KEYS), r["part_id"]) for r in plain.collect())
    assert plain.schema["part_id"].dataType == routed.schema["part_id"].dataType
