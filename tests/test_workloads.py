"""Directions of the study on the given tables, with the same headroom (none) for every method, and the joins of boxes against brute force."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenbox.operators import index, quality, router
from evenbox.operators import spatial_join as sj
from evenbox.operators.learn import learn, learn_distributed
from evenbox.operators.meeting import meeting
from evenbox.sources import tables as T

STUDY = ("str", "kd", "z", "hilbert")


def boxes(spark, n, side, seed, tag):
    random = np.random.default_rng(seed)
    lo = random.random((n, 2)).round(2)
    hi = lo + (random.random((n, 2)) * side).round(2)
    rows = [(i, *map(float, (*a, *b))) for i, (a, b) in enumerate(zip(lo, hi, strict=True))]
    return rows, spark.createDataFrame(rows, f"id_{tag} int, x1_{tag} double, y1_{tag} double, x2_{tag} double, y2_{tag} double")


@pytest.mark.parametrize("sides", [(0.05, 0.05), (1.5, 0.02), (0.0, 0.4)])
def test_boxes_that_meet(spark, sides):
    left, a = boxes(spark, 120, sides[0], 1, "a")
    right, b = boxes(spark, 90, sides[1], 2, "b")
    want = {(p[0], q[0]) for p in left for q in right if p[1] <= q[3] and q[1] <= p[3] and p[2] <= q[4] and q[2] <= p[4]}
    ends = lambda t: ([f"x1_{t}", f"y1_{t}"], [f"x2_{t}", f"y2_{t}"])
    got = [(r["id_a"], r["id_b"]) for r in meeting(a, b, ends("a"), ends("b")).collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert meeting(a, b.where("false"), ends("a"), ends("b")).count() == 0
    assert meeting(a.where("false"), b, ends("a"), ends("b")).count() == 0


def test_neighbours_far_and_near(spark, tmp_path):
    """Queries inside, between and far outside the records, and more neighbours than a cell or the table has."""
    random = np.random.default_rng(5)
    points = np.concatenate([random.normal(0, 1, (150, 2)), random.normal(50, 1, (150, 2))]).round(3)
    rows = [(i, float(x), float(y), 10, float(i % 97) / 97) for i, (x, y) in enumerate(points)]
    df = spark.createDataFrame(rows, "id long, x double, y double, bytes long, kh double")
    idx = index.write_index(df, learn(df, "mbs_count", 200).layout, f"{tmp_path}/near", block=200)
    at = [(0, 0.0, 0.0), (1, 25.0, 25.0), (2, 500.0, -300.0), (3, 50.5, 49.0)]
    asked = spark.createDataFrame(at, "qid int, q_x double, q_y double")
    for k in (1, 7, 400):
        got = {}
        for r in idx.knn(asked, k, ["id"]).collect():
            got.setdefault(r["qid"], {})[r["rank"]] = r["id"]
        for q, x, y in at:
            far = sorted((float((p[0] - x) ** 2 + (p[1] - y) ** 2), i) for i, p in enumerate(points))
            assert [got[q][i + 1] for i in range(min(k, 300))] == [i for _, i in far[:k]]


def test_byte_balance_without_headroom(spark, small):
    """Records of uneven size: the byte-balanced layout has the least deviation; where size follows place, under half of every baseline's."""
    for table, factor in (("documents", 0.5), ("documents_hash", 1.0)):
        df = T.points(spark, small, table).cache()
        deviation = {m: quality.size_deviation(quality.manifest(router.route(df, learn(df, m, 1 << 15, headroom=0.0).layout))).first()[0] for m in ("mbs_bytes", *STUDY)}
        df.unpersist()
        assert all(deviation["mbs_bytes"] < factor * deviation[m] for m in STUDY)


def test_phases_and_equal_headroom(spark, small):
    df = T.points(spark, small, "lineitem")
    for method in ("mbs_count", *STUDY):
        plain, eased = learn(df, method, 1 << 14, headroom=0.0), learn(df, method, 1 << 14, headroom=0.6)
        assert set(plain.phases) == {"summary", "sample", "boundaries"} and plain.phases["boundaries"] == plain.seconds
        assert eased.layout.parts > plain.layout.parts


def test_a_join_reads_fewer_blocks_than_slabs(spark, small):
    """Fewer pairs of partitions than slabs without headroom, and fewer pairs of blocks with the same headroom for both."""
    cost = {}
    for headroom in (0.0, None):
        for method in ("mbs_count", "str"):
            out = []
            for df, key in ((T.segments(spark, small), "event_id"), (T.hour_boxes(spark, small), "hour")):
                df = df.selectExpr("*", "CAST(100 AS BIGINT) AS bytes", f"{T.key_hash(key)} AS kh", "(x1 + x2) / 2 AS x", "(y1 + y2) / 2 AS y")
                routed = router.route(df, learn(df, method, 1 << 12, headroom=headroom).layout)
                out.append(quality.with_blocks(quality.box_manifest(routed, sj.LO, sj.HI), 1 << 12))
            cost[headroom, method] = quality.join_cost(*out).first()
    assert cost[0.0, "mbs_count"]["pairs"] < cost[0.0, "str"]["pairs"]
    assert cost[None, "mbs_count"]["block_pairs"] < cost[None, "str"]["block_pairs"]
    assert cost[None, "mbs_count"]["block_reads"] < cost[None, "str"]["block_reads"]


def test_one_partition_for_each_record(spark):
    """The only box that holds a record, else the least enlargement among the leaves it meets."""
    random = np.random.default_rng(3)
    points, hashes = random.random((300, 2)), random.random(300)
    df = spark.createDataFrame([(float(x), float(y), float(h), 100) for (x, y), h in zip(points, hashes, strict=True)], "x double, y double, kh double, bytes long")
    layout = learn(df, "mbs_count", 3000).layout
    rows, asked = boxes(spark, 150, 0.2, 9, "q")
    found = router.route_auto(asked, layout.tree, router.box_frame(spark, layout), ("x1_q", "y1_q"), ("x2_q", "y2_q"))
    regions = layout.tree.regions(2)
    for r in found.collect():
        i, x1, y1, x2, y2 = rows[r["id_q"]]
        met = [p for p, (lo, hi) in regions.items() if x1 <= hi[0] and lo[0] <= x2 and y1 <= hi[1] and lo[1] <= y2]
        holding = [p for p in met if layout.boxes[p][0][0] <= x1 and layout.boxes[p][0][1] <= y1 and x2 <= layout.boxes[p][1][0] and y2 <= layout.boxes[p][1][1]]
        area = lambda b: (b[1][0] - b[0][0]) * (b[1][1] - b[0][1])
        grown = lambda b: ([min(b[0][0], x1), min(b[0][1], y1)], [max(b[1][0], x2), max(b[1][1], y2)])
        best = min(area(grown(layout.boxes[p])) - area(layout.boxes[p]) for p in met)
        if len(holding) == 1:
            assert r["part_id"] == holding[0]
        else:
            own = layout.boxes[r["part_id"]]
            assert r["part_id"] in met and area(grown(own)) - area(own) == pytest.approx(best, abs=1e-12)
    assert asked.select(F.count("*")).first()[0] == found.count()


@pytest.mark.parametrize("variant", ["count", "bytes"])
def test_a_layout_grown_in_tasks(spark, small, tmp_path, variant):
    """Subtrees from several tasks make one tree: every record is routed to the leaf that counted it, and the layout can be written."""
    df = T.points(spark, small, "lineitem")
    learned = learn_distributed(df, 1 << 13, variant=variant, headroom=0.0, task_points=1000, top_points=500)
    layout = learned.layout
    found = {r["part_id"]: r["n_rows"] for r in quality.manifest(router.route(df, layout)).collect()}
    assert found == {i: n for i, n in layout.counts.items() if n} and layout.parts == len(layout.tree.axis) + 1
    sizes = [w if variant == "bytes" else n for n, w in zip(layout.counts.values(), layout.weights.values(), strict=True)]
    assert max(sizes) <= layout.spec.most * 1.001 and len(layout.tree.axis) > 4
    idx = index.write_index(df, layout, f"{tmp_path}/{variant}", block=1 << 13)
    assert idx.range_count((20000.0, 400.0), (60000.0, 1300.0)).first()["n"] == df.where("x BETWEEN 20000 AND 60000 AND y BETWEEN 400 AND 1300").count()
    assert learn_distributed(df.where("false"), 1 << 13).layout.parts == 1
