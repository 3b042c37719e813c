"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

#: layouts, routing, index queries, joins and measures: the methods themselves
HEADLINE = [
    "extent_lineitem",
    "byte_histogram_docs",
    "layout_mbs_plain",
    "layout_mbs_count",
    "layout_mbs_bytes",
    "route_points_tree",
    "route_points_case",
    "route_points_arrow",
    "route_boxes_tree",
    "str_2d",
    "z_keys",
    "hilbert_keys",
    "metric_overlap",
    "range_single",
    "range_batch",
    "join_intersects",
    "join_intersects_str",
    "knn",
    "tile_pyramid",
    "join_blocks",
]


def on_one_index(spark, sf_dir: str) -> dict[str, float]:
    """Building an index, and queries on it once it is there."""
    from pyspark.sql import functions as F

    from evenbox.cases.query_cases import _HIGH, _LOW
    from evenbox.operators.index import grid_queries, write_index
    from evenbox.operators.learn import learn
    from evenbox.sources import tables
    from evenbox.sources.io import work_path

    df, seconds, made = tables.points(spark, sf_dir, "lineitem"), {}, []
    asked = df.where(F.col("l_orderkey") % 100 == 0).selectExpr("monotonically_increasing_id() AS qid", "x AS q_x", "y AS q_y")
    steps = {
        "on_index_build": lambda: made.append(write_index(df, learn(df, "mbs_count", 1 << 18, ratio=0.1).layout, work_path(spark, "bench"), block=1 << 18)),
        "on_index_range": lambda: made[0].range((20000.0, 400.0), (60000.0, 1300.0)).count(),
        "on_index_batch_1200": lambda: made[0].range_batch(grid_queries(spark, _LOW, _HIGH, 1200, 0.0001)).count(),
        "on_index_knn": lambda: made[0].knn(asked, 10, ["l_orderkey", "l_linenumber"]).count(),
    }
    for name, step in steps.items():
        began = time.perf_counter()
        step()
        seconds[name] = round(time.perf_counter() - began, 3)
    return seconds


def main() -> None:
    from evenbox import workloads
    from evenbox.session import session

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = session("bench", f"local[{cpus}]", **{"spark.sql.shuffle.partitions": cpus, "spark.ui.enabled": "false", "spark.driver.memory": "16g", "spark.ui.showConsoleProgress": "false"})
    spark.sparkContext.setLogLevel("ERROR")
    queries, seconds = workloads.queries(), {}
    spark.range(1000).selectExpr("sum(id)").collect()
    for name in HEADLINE:
        began = time.perf_counter()
        queries[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
    seconds |= on_one_index(spark, sf_dir)
    total = round(sum(seconds.values()), 3)
    print(json.dumps({"metric": "headline queries, total", "value": total, "unit": "sec", "queries": seconds, "sf": sf_dir.rpartition("/sf")[2]}))
    spark.stop()


if __name__ == "__main__":
    main()
