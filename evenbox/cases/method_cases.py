"""Queries for size arithmetic, phase 1, splitting, layouts, baselines and routing."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenbox.functions import geom, sizing
from evenbox.functions.curves import hilbert_sql, hilbert_udf, lattice, z_key, z_key_sql
from evenbox.operators import phase1, quality, router
from evenbox.operators.learn import curve_runs_of, learn, learn_distributed
from evenbox.plans.baselines import fan_out, medians, quadrants, slabs, uniform
from evenbox.plans.cut import Counters, Node, Spec, axis_order, choose_cut, correct_weights, sweep, window
from evenbox.plans.grow import Tree, grow, plan_spec
from evenbox.registry import case
from evenbox.sources import tables as T

Frame = DataFrame
SIZES = [(9, 10), (450, 550), (5, 5), (1, 1), (3, 7), (95, 100), (1, 2)]
_SIZES_SQL = "(VALUES " + ", ".join(f"({a}, {b})" for a, b in SIZES) + ") v(least, most)"


def _sizes(spark: SparkSession) -> Frame:
    return spark.createDataFrame(SIZES, "least int, most int")


# --- size arithmetic, on the sizes of the given tables ------------------------------------------------

_SUPPLIED = "SELECT l_suppkey, count(*) AS size, CAST(min(l_quantity) AS INTEGER) AS least, CAST(max(l_quantity) AS INTEGER) AS most FROM lineitem GROUP BY l_suppkey"
#: records and bytes of the order lines of each number, and a sample of a tenth
_NUMBERED = "SELECT l_linenumber, count(*) // 10 AS n, count(*) * 100 AS data FROM lineitem GROUP BY l_linenumber"


def _supplied(spark: SparkSession, sf_dir: str) -> Frame:
    """Lines, least and largest quantity of each supplier."""
    lines = T.load(spark, sf_dir, "lineitem").groupBy("l_suppkey")
    return lines.agg(F.count("*").alias("size"), F.min("l_quantity").cast("int").alias("least"), F.max("l_quantity").cast("int").alias("most"))


def _numbered(spark: SparkSession, sf_dir: str) -> list[tuple[int, int, int]]:
    """A row for each line number, seven in all."""
    counts = T.load(spark, sf_dir, "lineitem").groupBy("l_linenumber").count().orderBy("l_linenumber").collect()
    return [(r["l_linenumber"], r["count"] // 10, r["count"] * 100) for r in counts]


@case("size_validity_grid", f"SELECT l_suppkey, size, v.least, v.most, (size + v.most - 1) // v.most <= size // v.least AS ok FROM ({_SUPPLIED}) s, {_SIZES_SQL}")
def size_validity_grid(spark, sf_dir):
    """Whether each supplier's lines can be tiled by leaves of each pair of bounds."""
    grid = _supplied(spark, sf_dir).select("l_suppkey", "size").crossJoin(F.broadcast(_sizes(spark)))
    return grid.select("l_suppkey", "size", "least", "most", sizing.fits_column(F.col("size"), F.col("least"), F.col("most")).alias("ok"))


@case("threshold_grid", f"SELECT l_suppkey, least, most, CASE WHEN least < most THEN CAST((least + most - least - 1) // (most - least) * least AS BIGINT) END AS threshold FROM ({_SUPPLIED})")
def threshold_grid(spark, sf_dir):
    """The size from which every size fits, with each supplier's least and largest quantity as bounds."""
    return _supplied(spark, sf_dir).select("l_suppkey", "least", "most", sizing.always_fits_column(F.col("least"), F.col("most")).alias("threshold"))


@case("witness_sizes", f"""SELECT CAST(size AS BIGINT) AS size, least, most, CAST(leaf AS BIGINT) AS leaf, CAST(least + greatest(0, least(most - least, size - least * parts - leaf * (most - least))) AS BIGINT) AS n
FROM (SELECT size, least, most, (size + most - 1) // most AS parts, unnest(range((size + most - 1) // most)) AS leaf FROM range(1, 201) r(size), {_SIZES_SQL} WHERE (size + most - 1) // most <= size // least)""".replace("greatest(0, least(most - least,", "greatest(0, LEAST(most - least,"))
def witness_sizes(spark, sf_dir):
    rows = [(s, a, b, i, n) for s in range(1, 201) for a, b in SIZES for i, n in enumerate(sizing.witness_sizes(s, a, b))]
    return spark.createDataFrame(pa.table([pa.array(c) for c in zip(*rows, strict=True)], ["size", "least", "most", "leaf", "n"])).select("size", F.col("least").cast("int"), F.col("most").cast("int"), "leaf", "n")


_RANGES = [(28, 9, 10), (1000, 450, 550), (63, 9, 10), (31, 9, 10), (900, 95, 100), (40, 5, 5)]


#: islands of the cuts that leave both sides of a total tileable; {queries} gives total, least, most
VALID_RANGES_SQL = """WITH q(total, least, most) AS ({queries}),
l AS (SELECT *, unnest(range(1, total // least + 1)) AS i FROM q), r AS (SELECT *, unnest(range(1, total // least + 1)) AS j FROM l),
p AS (SELECT total, least, most, greatest(i * least, total - j * most) AS a, LEAST(i * most, total - j * least) AS b FROM r),
o AS (SELECT *, max(b) OVER (PARTITION BY total, least, most ORDER BY a, b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM p WHERE a <= b AND b > 0 AND a < total),
g AS (SELECT *, sum(CASE WHEN reach IS NULL OR a > reach THEN 1 ELSE 0 END) OVER (PARTITION BY total, least, most ORDER BY a, b ROWS UNBOUNDED PRECEDING) AS island FROM o)
SELECT {columns} FROM g GROUP BY total, least, most, island"""


@case("valid_ranges", VALID_RANGES_SQL.format(queries="VALUES " + ", ".join(map(str, _RANGES)), columns="total, least, most, CAST(min(a) AS BIGINT) AS low, CAST(max(b) AS BIGINT) AS high"))
def valid_ranges(spark, sf_dir):
    rows = [(*q, int(a), int(b)) for q in _RANGES for a, b in sizing.cut_ranges(*q)]
    return spark.createDataFrame(rows, "total int, least int, most int, low long, high long")


@case("capacity_grid", f"SELECT l_linenumber, n, b AS block, d AS data, greatest(1, (n * b + d - 1) // d) AS most, greatest(1, 3 * greatest(1, (n * b + d - 1) // d) // 10) AS plain_least, greatest(1, 95 * greatest(1, (n * b + d - 1) // d) // 100) AS balanced_least, (d + ((d + b - 1) // b) - 1) // ((d + b - 1) // b) AS weight_most FROM (SELECT l_linenumber, n, data AS d FROM ({_NUMBERED})), (SELECT CAST(y * 65536 AS BIGINT) AS b FROM range(1, 5) t(y))")
def capacity_grid(spark, sf_dir):
    """Capacities for the lines of each number, sampled by a tenth, at four block sizes."""
    rows = []
    for number, n, data in _numbered(spark, sf_dir):
        for block in range(65536, 5 * 65536, 65536):
            most = sizing.count_capacity(n, block, data)
            rows.append((number, n, block, data, most, sizing.min_fill(most, 0.3), sizing.min_fill(most, 0.95), int(sizing.weight_capacity(data, sizing.ceil_div(data, block)))))
    return spark.createDataFrame(rows, "l_linenumber int, n long, block long, data long, most long, plain_least long, balanced_least long, weight_most long")


#: bytes of a sample record: an event's properties and two coordinates, the mean of its type rounded up
_POINT_BYTES = "SELECT event_type, CAST((sum(16 + coalesce(strlen(props), 0)) + count(*) - 1) // count(*) AS BIGINT) AS point_bytes FROM events GROUP BY event_type"


@case("sample_need_grid", f"""SELECT event_type, alpha, block_mb, point_bytes, CAST(CASE WHEN least < most THEN (least + most - least - 1) // (most - least) * least END AS BIGINT) AS points, CAST(CASE WHEN least < most THEN (least + most - least - 1) // (most - least) * least * point_bytes END AS BIGINT) AS bytes
FROM (SELECT *, greatest(1, alpha * most // 100) AS least FROM (SELECT event_type, alpha, block_mb, point_bytes, (block_mb * 1048576 + 100 * point_bytes - 1) // (100 * point_bytes) AS most FROM ({_POINT_BYTES}), (VALUES (80), (90), (95)) a(alpha), (VALUES (64), (128)) b(block_mb)))""")
def sample_need_grid(spark, sf_dir):
    """The sample that is sure to fit, for records of each event type."""
    size = F.lit(16) + F.coalesce(F.octet_length("props"), F.lit(0))
    kinds = T.load(spark, sf_dir, "events").groupBy("event_type").agg(F.sum(size).alias("b"), F.count("*").alias("n")).collect()  # a row for each type
    rows = [(r["event_type"], a, mb, p := sizing.ceil_div(r["b"], r["n"]), *sizing.sample_needed(a / 100, mb << 20, 0.01, p)) for r in kinds for a in (80, 90, 95) for mb in (64, 128)]
    return spark.createDataFrame(rows, "event_type string, alpha int, block_mb int, point_bytes long, points long, bytes long")


@case("str_fanout", f"SELECT l_linenumber, parts, d, min(f) AS fan, CAST(min(f) ** d AS BIGINT) AS cells FROM (SELECT l_linenumber, CAST((data + 65535) // 65536 AS BIGINT) AS parts FROM ({_NUMBERED})), range(2, 10) t(d), range(1, 20000) u(f) WHERE CAST(f AS DOUBLE) ** d >= parts GROUP BY l_linenumber, parts, d")
def str_fanout(spark, sf_dir):
    """Slabs for each axis, for the partitions of 64 kB that the lines of each number fill."""
    rows = [(number, p, d, f := fan_out(p, d), f**d) for number, _, data in _numbered(spark, sf_dir) for p in [sizing.ceil_div(data, 65536)] for d in range(2, 10)]
    return spark.createDataFrame(rows, "l_linenumber int, parts long, d long, fan long, cells long")


# --- phase 1 --------------------------------------------------------------------------------------


def _extent(name: str) -> None:
    sql = f"SELECT count(*) AS n_rows, CAST(sum(bytes) AS BIGINT) AS n_bytes, min(x) AS min_x, max(x) AS max_x, min(y) AS min_y, max(y) AS max_y FROM ({T.points_sql(name)})"
    case(f"extent_{name}", sql)(lambda spark, sf_dir: phase1.summarize(T.points(spark, sf_dir, name)))


for _name in ("lineitem", "orders", "events", "documents", "documents_hash", "pages"):
    _extent(_name)


@case("doc_bytes", "SELECT doc_id, CAST(strlen(text) AS BIGINT) AS bytes FROM documents")
def doc_bytes(spark, sf_dir):
    return T.points(spark, sf_dir, "documents").select("doc_id", "bytes")


@case("segment_boxes", f"SELECT * FROM ({T.SEGMENTS_SQL})")
def segment_boxes(spark, sf_dir):
    return T.segments(spark, sf_dir)


@case("hour_boxes", f"SELECT event_type, CAST(hour AS BIGINT) AS hour, x1, y1, x2, y2, n FROM ({T.HOUR_BOXES_SQL})")
def hour_boxes(spark, sf_dir):
    return T.hour_boxes(spark, sf_dir)


@case("anchor_points", f"SELECT user_id, event_id, (x1 + x2) / 2 AS cx, (y1 + y2) / 2 AS cy FROM ({T.SEGMENTS_SQL})")
def anchor_points(spark, sf_dir):
    centre = geom.centre(geom.cols(("x1", "y1")), geom.cols(("x2", "y2")))
    return T.segments(spark, sf_dir).select("user_id", "event_id", centre[0].alias("cx"), centre[1].alias("cy"))


@case("sample_bernoulli")
def sample_bernoulli(spark, sf_dir):
    return phase1.sample_fraction(T.points(spark, sf_dir, "lineitem"), 0.01, 7)


_SAMPLED = f"SELECT * FROM ({T.points_sql('lineitem')}) WHERE CAST(round(kh * {T.MODULUS}) AS BIGINT) % {T.MODULUS} < 100000"


@case("sample_keyed", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, x, y FROM ({_SAMPLED})")
def sample_keyed(spark, sf_dir):
    return phase1.sample_by_hash(T.points(spark, sf_dir, "lineitem"), 100000 / T.MODULUS).select(*T.LINE_KEYS, "x", "y")


@case("sample_capped", f"SELECT event_id, x, y FROM ({T.points_sql('events')}) ORDER BY kh, event_id LIMIT 200")
def sample_capped(spark, sf_dir):
    return phase1.sample_capped(T.points(spark, sf_dir, "events"), 200, ["event_id"]).select("event_id", "x", "y")


_GRID = 16
_CELL = f"(CAST(greatest(0, LEAST({_GRID - 1}, floor((x - 0.0) / 10007.0 * {_GRID}))) AS BIGINT) * {_GRID} + CAST(greatest(0, LEAST({_GRID - 1}, floor((y - 0.0) / 10009.0 * {_GRID}))) AS BIGINT))"
_DOCS = T.points_sql("documents_hash")
_DOC_SAMPLE = f"SELECT *, {_CELL} AS cell FROM ({_DOCS}) WHERE CAST(round(kh * {T.MODULUS}) AS BIGINT) % {T.MODULUS} < 300000"
_HISTOGRAM = f"SELECT {_CELL} AS cell, CAST(sum(bytes) AS BIGINT) AS bytes, count(*) AS n FROM ({_DOCS}) GROUP BY 1"
_LOW, _HIGH, _GRIDS = (0.0, 0.0), (10007.0, 10009.0), (_GRID, _GRID)


def _doc_sample(spark, sf_dir):
    return phase1.sample_by_hash(T.points(spark, sf_dir, "documents_hash"), 300000 / T.MODULUS)


def _doc_histogram(spark, sf_dir):
    return phase1.byte_histogram(T.points(spark, sf_dir, "documents_hash"), _LOW, _HIGH, _GRIDS)


@case("byte_histogram_docs", _HISTOGRAM)
def byte_histogram_docs(spark, sf_dir):
    return _doc_histogram(spark, sf_dir)


@case("sample_cell_counts", f"SELECT cell, count(*) AS k FROM ({_DOC_SAMPLE}) GROUP BY cell")
def sample_cell_counts(spark, sf_dir):
    return _doc_sample(spark, sf_dir).groupBy(phase1.cell_number(_LOW, _HIGH, _GRIDS).alias("cell")).agg(F.count("*").alias("k"))


@case("point_weights_docs", f"SELECT s.doc_id, round(h.bytes / count(*) OVER (PARTITION BY s.cell), 6) AS w FROM ({_DOC_SAMPLE}) s JOIN ({_HISTOGRAM}) h ON s.cell = h.cell")
def point_weights_docs(spark, sf_dir):
    weighted = phase1.weigh(_doc_sample(spark, sf_dir), _doc_histogram(spark, sf_dir), phase1.cell_number(_LOW, _HIGH, _GRIDS), "drop", _GRIDS)
    return weighted.select("doc_id", F.round("w", 6).alias("w"))


@case("orphan_cells", f"SELECT cell, bytes FROM ({_HISTOGRAM}) WHERE cell NOT IN (SELECT cell FROM ({_DOC_SAMPLE}))")
def orphan_cells(spark, sf_dir):
    cells = _doc_sample(spark, sf_dir).select(phase1.cell_number(_LOW, _HIGH, _GRIDS).alias("cell")).distinct()
    return _doc_histogram(spark, sf_dir).join(F.broadcast(cells), "cell", "left_anti").select("cell", "bytes")


@case("weight_totals", f"SELECT policy, round(CAST(sum(bytes) AS DOUBLE), 3) AS total FROM ({_HISTOGRAM}), (VALUES ('nearest'), ('rescale')) p(policy) GROUP BY policy")
def weight_totals(spark, sf_dir):
    """Both policies that keep orphans' bytes keep all bytes."""
    out = None
    for policy in ("nearest", "rescale"):
        one = phase1.weigh(_doc_sample(spark, sf_dir), _doc_histogram(spark, sf_dir), phase1.cell_number(_LOW, _HIGH, _GRIDS), policy, _GRIDS).agg(F.round(F.sum("w"), 3).alias("total")).select(F.lit(policy).alias("policy"), "total")
        out = one if out is None else out.unionByName(one)
    return out


# --- splitting ------------------------------------------------------------------------------------

#: the sample on whole numbers (cents, days), so that costs are exact
_LATTICE = f"SELECT CAST(round(x * 100) AS BIGINT) AS x, CAST(y AS BIGINT) AS y, kh, bytes FROM ({_SAMPLED})"


def _cuts_sql(source: str) -> str:
    """Costs of all cuts of both axes; cuts(axis, k, n, area, margin, overlap, left_bytes, all_bytes)."""
    one = []
    for axis, (a, b) in enumerate((("x", "y"), ("y", "x"))):
        order = f"ORDER BY {a}, {b}, kh"
        frames = ", ".join(f"{f}({c}) OVER ({order} ROWS BETWEEN {span}) AS {side}_{f}_{c}" for c in ("x", "y") for f in ("min", "max") for side, span in (("l", "UNBOUNDED PRECEDING AND CURRENT ROW"), ("r", "1 FOLLOWING AND UNBOUNDED FOLLOWING")))
        one.append(f"SELECT {axis} AS axis, row_number() OVER ({order}) AS k, count(*) OVER () AS n, sum(bytes) OVER ({order} ROWS UNBOUNDED PRECEDING) AS left_bytes, sum(bytes) OVER () AS all_bytes, {frames} FROM ({source})")
    box = lambda s, c: f"({s}_max_{c} - {s}_min_{c})"
    shared = " * ".join(f"greatest(0, LEAST(l_max_{c}, r_max_{c}) - greatest(l_min_{c}, r_min_{c}))" for c in ("x", "y"))
    return f"SELECT axis, k, n, left_bytes, all_bytes, {box('l', 'x')} * {box('l', 'y')} + {box('r', 'x')} * {box('r', 'y')} AS area, {box('l', 'x')} + {box('l', 'y')} + {box('r', 'x')} + {box('r', 'y')} AS margin, {shared} AS overlap FROM ({' UNION ALL '.join(one)}) WHERE k < n"


def _first_cut_sql(valid: str, inside: str, source: str = _LATTICE) -> str:
    return f"""WITH cuts AS ({_cuts_sql(source)}), pick AS (SELECT axis FROM cuts WHERE {inside} GROUP BY axis ORDER BY sum(margin), axis LIMIT 1)
SELECT axis, k, CAST(area AS BIGINT) AS area, CAST(margin AS BIGINT) AS margin FROM cuts WHERE axis IN (SELECT axis FROM pick) AND {inside} AND {valid} ORDER BY area, margin, overlap, abs(k - n / 2.0), k LIMIT 1"""


def _lattice_node(spark, sf_dir, weights=None) -> Node:
    rows = phase1.sample_by_hash(T.points(spark, sf_dir, "lineitem"), 100000 / T.MODULUS).selectExpr("CAST(round(x * 100) AS BIGINT) AS x", "y", "kh")
    points, hashes, _ = phase1.to_numpy(rows, ("x", "y"))
    w = np.ones(len(points)) if weights is None else weights(points)
    return Node(np.arange(len(points)), points, points, hashes, w)


def _first_cut(spark, sf_dir, spec_of, weights=None) -> Frame:
    node = _lattice_node(spark, sf_dir, weights)
    axis, order, k, _ = choose_cut(node, spec_of(len(node)), Counters())
    costs = sweep(node.points, order)
    return spark.createDataFrame([(axis, int(k), int(costs.area[k - 1]), int(costs.margin[k - 1]))], "axis int, k long, area long, margin long")


@case("axis_margin_totals", f"SELECT axis, CAST(sum(margin) AS BIGINT) AS margin FROM ({_cuts_sql(_LATTICE)}) WHERE k BETWEEN ceil(0.4 * n) AND n - ceil(0.4 * n) GROUP BY axis")
def axis_margin_totals(spark, sf_dir):
    node = _lattice_node(spark, sf_dir)
    low, high = window(len(node), 1, 0.4)
    rows = [(a, int(sweep(node.points, axis_order(node.raw, node.hashes, a)).margin[low - 1 : high].sum())) for a in (0, 1)]
    return spark.createDataFrame(rows, "axis int, margin long")


@case("first_cut_plain", _first_cut_sql("true", "k BETWEEN 19 AND n - 19"))
def first_cut_plain(spark, sf_dir):
    return _first_cut(spark, sf_dir, lambda n: Spec("plain", 19, 64, 0.0))


@case("first_cut_rho", _first_cut_sql("true", "k BETWEEN ceil(0.4 * n) AND n - ceil(0.4 * n)"))
def first_cut_rho(spark, sf_dir):
    return _first_cut(spark, sf_dir, lambda n: Spec("plain", 19, 64, 0.4))


@case("first_cut_balanced", _first_cut_sql("(k + 63) // 64 <= k // 60 AND (n - k + 63) // 64 <= (n - k) // 60", "k BETWEEN ceil(0.4 * n) AND n - ceil(0.4 * n)"))
def first_cut_balanced(spark, sf_dir):
    return _first_cut(spark, sf_dir, lambda n: Spec("count", 60, 64, 0.4))


#: points of 50 to 150 bytes, by their day
_UNEVEN = _LATTICE.replace("kh, bytes", "kh, 50 + CAST(y AS BIGINT) % 101 AS bytes")
_TILED = "(left_bytes + 6399) // 6400 <= left_bytes // 5500 AND (all_bytes - left_bytes + 6399) // 6400 <= (all_bytes - left_bytes) // 5500"


@case("first_cut_weighted", _first_cut_sql(_TILED, "k BETWEEN ceil(0.4 * n) AND n - ceil(0.4 * n)", _UNEVEN))
def first_cut_weighted(spark, sf_dir):
    return _first_cut(spark, sf_dir, lambda n: Spec("bytes", 5500, 6400, 0.4), lambda points: 50.0 + points[:, 1] % 101)


@case("point_positions", f"SELECT doc_id, CAST(sum(bytes) OVER (ORDER BY x, y, kh ROWS UNBOUNDED PRECEDING) AS BIGINT) AS position FROM ({_DOC_SAMPLE})")
def point_positions(spark, sf_dir):
    table = _doc_sample(spark, sf_dir).select("doc_id", "x", "y", "kh", "bytes").toArrow().to_pandas()
    points = table[["x", "y"]].to_numpy()
    order = axis_order(points, table["kh"].to_numpy(), 0)
    rows = zip(table["doc_id"].to_numpy()[order].tolist(), np.cumsum(table["bytes"].to_numpy()[order]).tolist(), strict=True)
    return spark.createDataFrame(list(rows), "doc_id long, position long")


@case("weight_correction_demo", "SELECT CAST(i AS BIGINT) AS i, w FROM (VALUES (0, 200.0::DOUBLE), (1, 200.0), (2, 100.0), (3, 300.0), (4, 200.0)) t(i, w)")
def weight_correction_demo(spark, sf_dir):
    moved, _ = correct_weights(np.full(5, 200.0), sizing.cut_ranges(1000, 450, 550))
    return spark.createDataFrame(list(enumerate(moved.tolist())), "i long, w double")


# --- layouts --------------------------------------------------------------------------------------


def _leaves(spark, layout) -> Frame:
    rows = [(layout.method, i, layout.counts[i], float(layout.weights[i]), [float(v) for v in layout.boxes[i][0]], [float(v) for v in layout.boxes[i][1]]) for i in sorted(layout.boxes)]
    return spark.createDataFrame(rows, "method string, leaf int, n long, weight double, lo array<double>, hi array<double>")


def _layout_case(method: str, name: str, table: str, block: int) -> None:
    case(name)(lambda spark, sf_dir: _leaves(spark, learn(T.points(spark, sf_dir, table), method, block).layout))


for _m in ("mbs_plain", "mbs_count", "mbs_bytes"):
    _layout_case(_m, f"layout_{_m}", "documents_hash", 1 << 17)
_layout_case("rstar_insert", "layout_rstar_insert", "documents_hash", 1 << 17)


def _axes(d: int) -> list[str]:
    return [f"a{i}" for i in range(d)]


def _multi(d: int, source) -> None:
    def run(spark, sf_dir):
        return _leaves(spark, learn(source(spark, sf_dir, d), "mbs_count", 1 << 18, _axes(d), 0.1).layout)

    case(f"layout_mbs_d{d}")(run)


for _d, _source in ((3, T.diagonal), (4, T.trips), (5, T.trips), (7, T.trips), (9, T.diagonal)):
    _multi(_d, _source)


@case("layout_distributed")
def layout_distributed(spark, sf_dir):
    """Subtrees finished in tasks and hung below the first levels."""
    return _leaves(spark, learn_distributed(T.points(spark, sf_dir, "lineitem"), 1 << 17, ratio=0.5, task_points=5000, top_points=2000).layout)


@case("layout_counters")
def layout_counters(spark, sf_dir):
    """How often each variant relaxed the window, corrected weights, cut at a tie, took another axis, or left a leaf out of bounds."""
    df = T.points(spark, sf_dir, "documents_hash")
    rows = [(m, name, count) for m in ("mbs_plain", "mbs_count", "mbs_bytes") for name, count in vars(learn(df, m, 1 << 17, headroom=0.0).layout.counters).items()]
    return spark.createDataFrame(rows, "method string, counter string, times long")


_ROUTED_DOCS = "SELECT count(*) AS n_rows, CAST(sum(bytes) AS BIGINT) AS bytes, 0 AS outside FROM"


def _invariant(method: str, table: str, sql: str) -> None:
    """Every record of the table is in one partition, and inside the box that was learned for it from the whole table."""

    def run(spark, sf_dir):
        df = T.points(spark, sf_dir, table)
        layout = learn(df, method, 1 << 17, headroom=0.0).layout
        boxes = router.box_frame(spark, layout)
        routed = router.route(df, layout).join(boxes, "part_id", "left")
        inside = (F.col("x") >= F.col("blo")[0]) & (F.col("x") <= F.col("bhi")[0]) & (F.col("y") >= F.col("blo")[1]) & (F.col("y") <= F.col("bhi")[1])
        return routed.agg(F.count("*").alias("n_rows"), F.sum("bytes").alias("bytes"), F.sum(F.when(F.coalesce(inside, F.lit(False)), 0).otherwise(1)).cast("int").alias("outside"))

    case(f"layout_holds_{method}", f"{_ROUTED_DOCS} ({sql})")(run)


for _method in ("mbs_plain", "mbs_count", "mbs_bytes", "str", "kd", "quad", "grid", "rstar_insert"):
    _invariant(_method, "documents_hash", T.points_sql("documents_hash"))


@case("leaf_bounds_count", f"SELECT 0 AS outside, count(*) AS n FROM ({_SAMPLED})")
def leaf_bounds_count(spark, sf_dir):
    """No leaf lies outside the bounds, and no sample point is lost."""
    sample = phase1.sample_by_hash(T.points(spark, sf_dir, "lineitem"), 100000 / T.MODULUS)
    points, hashes, _ = phase1.to_numpy(sample, ("x", "y"))
    layout = grow(points, hashes, Spec("count", 50, 55))
    outside = sum(not layout.spec.least <= n <= layout.spec.most for n in layout.counts.values())
    return spark.createDataFrame([(outside, sum(layout.counts.values()))], "outside int, n long")


@case("leaf_bounds_bytes", f"SELECT 0 AS outside, 0 AS relaxed, CAST(sum(bytes) AS BIGINT) AS bytes FROM ({_DOCS})")
def leaf_bounds_bytes(spark, sf_dir):
    df = T.points(spark, sf_dir, "documents_hash")
    layout = learn(df, "mbs_bytes", 1 << 18, headroom=0.0).layout
    slack = 1e-6 * layout.spec.most
    outside = sum(not layout.spec.least - slack <= w <= layout.spec.most + slack for w in layout.weights.values()) if layout.parts > 1 else 0
    relaxed = layout.counters.unbalanced + layout.counters.oversize
    return spark.createDataFrame([(outside, relaxed, round(sum(layout.weights.values())))], "outside int, relaxed int, bytes long")


# --- routing --------------------------------------------------------------------------------------

#: a literal tree of three levels over price and ship day; leaves 0..4
FIXED = Tree([0, 1, 1, 0], [[50000.0, 1200.0, 0.5], [900.0, 40000.0, 0.25], [1500.0, 70000.0, 0.5], [75000.0, 1600.0, 0.75]], [1, -1, 3, -3], [2, -2, -5, -4])
_FIXED_CASE = """CASE WHEN (x, y, kh) <= (50000.0, 1200.0, 0.5) THEN CASE WHEN (y, x, kh) <= (900.0, 40000.0, 0.25) THEN 0 ELSE 1 END
ELSE CASE WHEN (y, x, kh) <= (1500.0, 70000.0, 0.5) THEN CASE WHEN (x, y, kh) <= (75000.0, 1600.0, 0.75) THEN 2 ELSE 3 END ELSE 4 END END"""
_ROUTED = f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, x, y, bytes, {_FIXED_CASE} AS part_id FROM ({T.points_sql('lineitem')})"


def _routed(spark, sf_dir, mode="tree") -> Frame:
    return router.route_points(T.points(spark, sf_dir, "lineitem"), FIXED, mode=mode)


for _mode in ("tree", "case", "arrow"):
    case(f"route_points_{_mode}", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, x, y, part_id FROM ({_ROUTED})")(lambda spark, sf_dir, mode=_mode: _routed(spark, sf_dir, mode).select(*T.LINE_KEYS, "x", "y", "part_id"))

#: shipment boxes: days from shipping over a quantity of days, by discounted to taxed price
_SHIP = "days"


def shipments(spark, sf_dir) -> Frame:
    day = T.days("l_shipdate", "spark")
    return T.load(spark, sf_dir, "lineitem").selectExpr(*T.LINE_KEYS, "l_extendedprice * (1 - l_discount) AS x1", f"{day} AS y1", "l_extendedprice * (1 + l_tax) AS x2", f"{day} + l_quantity AS y2", "CAST(100 AS BIGINT) AS bytes", f"{T.key_hash(*T.LINE_KEYS)} AS kh")


_DAY = T.days("l_shipdate", "duck")
SHIPMENTS_SQL = f"SELECT {', '.join(T.LINE_KEYS)}, l_extendedprice * (1 - l_discount) AS x1, {_DAY} AS y1, l_extendedprice * (1 + l_tax) AS x2, {_DAY} + l_quantity AS y2, CAST(100 AS BIGINT) AS bytes, {T.key_hash(*T.LINE_KEYS)} AS kh FROM lineitem"
_REGIONS = "(VALUES (0, '-inf'::DOUBLE, '-inf'::DOUBLE, 50000.0::DOUBLE, 900.0::DOUBLE), (1, '-inf', 900.0, 50000.0, 'inf'), (2, 50000.0, '-inf', 75000.0, 1500.0), (3, 75000.0, '-inf', 'inf', 1500.0), (4, 50000.0, 1500.0, 'inf', 'inf')) r(part_id, rx1, ry1, rx2, ry2)"


@case("route_boxes_tree", f"SELECT part_id, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM ({SHIPMENTS_SQL}) JOIN {_REGIONS} ON x1 <= rx2 AND rx1 <= x2 AND y1 <= ry2 AND ry1 <= y2 GROUP BY part_id")
def route_boxes_tree(spark, sf_dir):
    return router.route_boxes(shipments(spark, sf_dir), FIXED, ("x1", "y1"), ("x2", "y2")).groupBy("part_id").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


#: a box inside each region of the fixed tree
_INNER = [(0, (1000.0, 0.0), (50000.0, 900.0)), (1, (1000.0, 901.0), (50000.0, 2600.0)), (2, (50000.5, 0.0), (75000.0, 1500.0)), (3, (75000.5, 0.0), (105000.0, 1400.0)), (4, (50001.0, 1501.0), (105000.0, 2600.0))]
_INNER_SQL = "(VALUES " + ", ".join(f"({i}, {a[0]}::DOUBLE, {a[1]}::DOUBLE, {b[0]}::DOUBLE, {b[1]}::DOUBLE)" for i, a, b in _INNER) + ") b(part_id, bx1, by1, bx2, by2)"


@case("route_auto", f"""WITH met AS (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, x1, y1, x2, y2, b.part_id, bx1 <= x1 AND x2 <= bx2 AND by1 <= y1 AND y2 <= by2 AS holds,
(greatest(bx2, x2) - least(bx1, x1)) * (greatest(by2, y2) - least(by1, y1)) - (bx2 - bx1) * (by2 - by1) AS grow, (bx2 - bx1) * (by2 - by1) AS own
FROM ({SHIPMENTS_SQL}) JOIN {_REGIONS} ON x1 <= rx2 AND rx1 <= x2 AND y1 <= ry2 AND ry1 <= y2 JOIN {_INNER_SQL} ON b.part_id = r.part_id),
best AS (SELECT *, count(*) FILTER (WHERE holds) OVER w AS held, row_number() OVER (PARTITION BY l_orderkey, l_linenumber, l_partkey, l_suppkey, x1, y1 ORDER BY NOT holds, part_id) AS first_holder,
row_number() OVER (PARTITION BY l_orderkey, l_linenumber, l_partkey, l_suppkey, x1, y1 ORDER BY grow, own, part_id) AS least FROM met WINDOW w AS (PARTITION BY l_orderkey, l_linenumber, l_partkey, l_suppkey, x1, y1))
SELECT part_id, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM best WHERE CASE WHEN held = 1 THEN first_holder = 1 ELSE least = 1 END GROUP BY part_id""")
def route_auto(spark, sf_dir):
    """The one box that contains a record, else the least enlargement among the leaves it meets."""
    boxes = spark.createDataFrame([(i, list(a), list(b)) for i, a, b in _INNER], "part_id int, blo array<double>, bhi array<double>")
    routed = router.route_auto(shipments(spark, sf_dir), FIXED, boxes, ("x1", "y1"), ("x2", "y2"))
    return routed.groupBy("part_id").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


@case("route_anchor_boxes", f"SELECT part_id, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM (SELECT l_orderkey, {_FIXED_CASE} AS part_id FROM (SELECT l_orderkey, (x1 + x2) / 2 AS x, (y1 + y2) / 2 AS y, kh FROM ({SHIPMENTS_SQL}))) GROUP BY part_id")
def route_anchor_boxes(spark, sf_dir):
    return router.route_anchor(shipments(spark, sf_dir), FIXED, ("x1", "y1"), ("x2", "y2")).groupBy("part_id").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


@case("regions_cover", f"SELECT r.part_id, rx1, ry1, rx2, ry2, n FROM {_REGIONS} JOIN (SELECT part_id, count(*) AS n FROM ({_ROUTED}) GROUP BY part_id) c ON c.part_id = r.part_id")
def regions_cover(spark, sf_dir):
    """Every region with the records that are routed there."""
    held = _routed(spark, sf_dir).groupBy("part_id").agg(F.count("*").alias("n"))
    return router.regions(spark, FIXED, 2).join(held, "part_id").select("part_id", F.col("rlo")[0].alias("rx1"), F.col("rlo")[1].alias("ry1"), F.col("rhi")[0].alias("rx2"), F.col("rhi")[1].alias("ry2"), "n")


#: four boxes on cents and days for the assignment rules
BOXES = [(0, [0, 0], [4000000, 1000]), (1, [4500000, 0], [10000000, 900]), (2, [0, 1300], [5000000, 2400]), (3, [6000000, 1100], [9000000, 2500])]
_BOXES_SQL = "(VALUES " + ", ".join(f"({i}, {a[0]}::BIGINT, {a[1]}::BIGINT, {b[0]}::BIGINT, {b[1]}::BIGINT)" for i, a, b in BOXES) + ") b(part_id, bx1, by1, bx2, by2)"
_CENTS = f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(x * 100) AS BIGINT) AS x, CAST(y AS BIGINT) AS y FROM ({T.points_sql('lineitem')})"
_AREA = "(greatest(bx2, x) - LEAST(bx1, x)) * (greatest(by2, y) - LEAST(by1, y)) - (bx2 - bx1) * (by2 - by1)"
_MARGIN = "(greatest(bx2, x) - LEAST(bx1, x)) + (greatest(by2, y) - LEAST(by1, y)) - (bx2 - bx1) - (by2 - by1)"


def _cents(spark, sf_dir) -> Frame:
    return T.points(spark, sf_dir, "lineitem").selectExpr(*T.LINE_KEYS, "CAST(round(x * 100) AS BIGINT) AS x", "CAST(y AS BIGINT) AS y")


def _boxes(spark) -> Frame:
    return spark.createDataFrame(BOXES, "part_id int, blo array<long>, bhi array<long>")


for _by, _grow, _own in (("area", _AREA, "(bx2 - bx1) * (by2 - by1)"), ("margin", _MARGIN, "(bx2 - bx1) + (by2 - by1)")):
    case(f"route_min_{_by}", f"SELECT part_id, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM (SELECT * FROM ({_CENTS}), {_BOXES_SQL} QUALIFY row_number() OVER (PARTITION BY l_orderkey, l_linenumber, l_partkey, l_suppkey, x, y ORDER BY {_grow}, {_own}, part_id) = 1) GROUP BY part_id")(
        lambda spark, sf_dir, by=_by: router.route_enlarge(_cents(spark, sf_dir), _boxes(spark), ("x", "y"), ("x", "y"), by).groupBy("part_id").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))
    )

_SHARED = "greatest(0, LEAST(ux2, ox2) - greatest(ux1, ox1)) * greatest(0, LEAST(uy2, oy2) - greatest(uy1, oy1)) - greatest(0, LEAST(bx2, ox2) - greatest(bx1, ox1)) * greatest(0, LEAST(by2, oy2) - greatest(by1, oy1))"


@case("route_min_overlap", f"""WITH p AS (SELECT *, row_number() OVER () AS rid FROM ({_CENTS})), u AS (SELECT *, LEAST(bx1, x) AS ux1, LEAST(by1, y) AS uy1, greatest(bx2, x) AS ux2, greatest(by2, y) AS uy2 FROM p, {_BOXES_SQL}),
o AS (SELECT part_id AS oid, bx1 AS ox1, by1 AS oy1, bx2 AS ox2, by2 AS oy2 FROM {_BOXES_SQL}),
g AS (SELECT rid, l_orderkey, part_id, bx1, by1, bx2, by2, x, y, sum({_SHARED}) AS growth FROM u JOIN o ON oid <> part_id GROUP BY ALL)
SELECT part_id, count(*) AS n, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM (SELECT * FROM g QUALIFY row_number() OVER (PARTITION BY rid ORDER BY growth, {_AREA}, (bx2 - bx1) * (by2 - by1), part_id) = 1) GROUP BY part_id""")
def route_min_overlap(spark, sf_dir):
    return router.route_overlap(_cents(spark, sf_dir), _boxes(spark), ("x", "y"), ("x", "y")).groupBy("part_id").agg(F.count("*").alias("n"), F.sum("l_orderkey").alias("keys"))


# --- baselines ------------------------------------------------------------------------------------

_SUMMARY = "part_id, count(*) AS n, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y"


def _by_part(routed: Frame) -> Frame:
    return routed.groupBy("part_id").agg(F.count("*").alias("n"), F.min("x").alias("lo_x"), F.max("x").alias("hi_x"), F.min("y").alias("lo_y"), F.max("y").alias("hi_y"))


def _all_points(spark, sf_dir, name="lineitem"):
    return phase1.to_numpy(T.points(spark, sf_dir, name), ("x", "y"))[:2]


@case("str_2d", f"SELECT {_SUMMARY} FROM (SELECT x, y, CAST((a - 1) * 8 + ntile(8) OVER (PARTITION BY a ORDER BY y, x, kh) - 1 AS INTEGER) AS part_id FROM (SELECT *, ntile(8) OVER (ORDER BY x, y, kh) AS a FROM ({T.points_sql('lineitem')}))) GROUP BY part_id")
def str_2d(spark, sf_dir):
    layout = slabs(*_all_points(spark, sf_dir), 64)
    return _by_part(router.route(T.points(spark, sf_dir, "lineitem"), layout))


_TRIPS = f"SELECT l_extendedprice AS a0, l_quantity AS a1, l_discount AS a2, l_tax AS a3, {T.key_hash(*T.LINE_KEYS)} AS kh FROM lineitem"


def _nested_tiles(source: str, f: int, d: int) -> str:
    inner = f"SELECT *, 0 AS part FROM ({source})"
    for i in range(d):
        order = ", ".join(f"a{(i + j) % d}" for j in range(d))
        inner = f"SELECT * EXCLUDE (part), part * {f} + ntile({f}) OVER (PARTITION BY part ORDER BY {order}, kh) - 1 AS part FROM ({inner})"
    return inner


@case("str_4d", f"SELECT CAST(part AS INTEGER) AS part_id, count(*) AS n, max(a0) AS hi0, max(a1) AS hi1 FROM ({_nested_tiles(_TRIPS, 3, 4)}) GROUP BY part")
def str_4d(spark, sf_dir):
    df = T.trips(spark, sf_dir, 4)
    points, hashes, _ = phase1.to_numpy(df, _axes(4))
    routed = router.route_points(df, slabs(points, hashes, 81).tree, _axes(4))
    return routed.groupBy("part_id").agg(F.count("*").alias("n"), F.max("a0").alias("hi0"), F.max("a1").alias("hi1"))


@case("kd_8", f"""SELECT {_SUMMARY} FROM (SELECT x, y, CAST(p * 2 + ntile(2) OVER (PARTITION BY p ORDER BY x, y, kh) - 1 AS INTEGER) AS part_id FROM (SELECT *, q * 2 + ntile(2) OVER (PARTITION BY q ORDER BY y, x, kh) - 1 AS p
FROM (SELECT *, ntile(2) OVER (ORDER BY x, y, kh) - 1 AS q FROM ({T.points_sql('lineitem')})))) GROUP BY part_id""")
def kd_8(spark, sf_dir):
    return _by_part(router.route(T.points(spark, sf_dir, "lineitem"), medians(*_all_points(spark, sf_dir), 8)))


@case("kd_depth", "SELECT parts, CAST(ceil(log2(parts)) AS INTEGER) AS depth, CAST(2 ** ceil(log2(parts)) AS BIGINT) AS leaves, (SELECT least(4096, count(*)) FROM orders) AS points FROM (VALUES (5), (8), (100), (128)) p(parts)")
def kd_depth(spark, sf_dir):
    """Median trees over the 4096 orders of least hash."""
    points, hashes, _ = phase1.to_numpy(phase1.sample_capped(T.points(spark, sf_dir, "orders"), 4096, ["o_orderkey"]), ("x", "y"))
    rows = [(p, (layout := medians(points, hashes, p)).tree.depth(), layout.parts, len(points)) for p in (5, 8, 100, 128)]
    return spark.createDataFrame(rows, "parts int, depth int, leaves long, points long")


_BITS = 16
_TOP = (1 << _BITS) - 1
_CX = f"CAST(greatest(0, LEAST({_TOP}, floor((x - 900.0) / 104100.0 * {_TOP}))) AS BIGINT)"
_CY = f"CAST(greatest(0, LEAST({_TOP}, floor((y - 0.0) / 2500.0 * {_TOP}))) AS BIGINT)"


def _lattice_cells():
    return [lattice(F.col("x"), 900.0, 105000.0, _BITS), lattice(F.col("y"), 0.0, 2500.0, _BITS)]


@case("z_keys", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST({z_key_sql([_CX, _CY], _BITS)} AS BIGINT) AS zkey FROM ({T.points_sql('lineitem')})")
def z_keys(spark, sf_dir):
    return T.points(spark, sf_dir, "lineitem").select(*T.LINE_KEYS, z_key(_lattice_cells(), _BITS).alias("zkey"))


@case("geohash_prefix", f"SELECT CAST({z_key_sql([_CX, _CY], _BITS)} AS BIGINT) >> 22 AS prefix, count(*) AS n FROM ({T.points_sql('lineitem')}) GROUP BY 1")
def geohash_prefix(spark, sf_dir):
    return T.points(spark, sf_dir, "lineitem").groupBy(F.shiftright(z_key(_lattice_cells(), _BITS), 22).alias("prefix")).agg(F.count("*").alias("n"))


_EVENT_CELL = [f"CAST(greatest(0, LEAST(1023, floor(({c} - ({lo})) / CASE WHEN ({hi}) > ({lo}) THEN ({hi}) - ({lo}) ELSE 1.0 END * 1023))) AS BIGINT)" for c, lo, hi in (("x", "x0", "x9"), ("y", "y0", "y9"))]
_EVENT_PTS = f"SELECT *, min(x) OVER () AS x0, max(x) OVER () AS x9, min(y) OVER () AS y0, max(y) OVER () AS y9 FROM ({T.points_sql('events')})"
_Z_EVENTS = f"SELECT x, y, CAST({z_key_sql(_EVENT_CELL, 10)} AS BIGINT) AS key FROM ({_EVENT_PTS})"
_CUTS = "SELECT DISTINCT key AS cut FROM (SELECT key, row_number() OVER (ORDER BY key) AS r, count(*) OVER () AS n FROM k) WHERE r IN (SELECT n * i // 20 FROM range(1, 20) t(i))"


@case("z_partitions", f"WITH k AS ({_Z_EVENTS}), c AS ({_CUTS}) SELECT {_SUMMARY} FROM (SELECT x, y, CAST((SELECT count(*) FROM c WHERE cut < key) AS INTEGER) AS part_id FROM k) GROUP BY part_id")
def z_partitions(spark, sf_dir):
    df = T.points(spark, sf_dir, "events")
    return _by_part(router.route(df, curve_runs_of(df, 20, "z", 10)))


_HILBERT = hilbert_sql(_CX, _CY, _BITS, f"({T.points_sql('lineitem')})", "l_orderkey, l_linenumber, l_partkey, l_suppkey")


@case("hilbert_keys", _HILBERT)
def hilbert_keys(spark, sf_dir):
    return T.points(spark, sf_dir, "lineitem").select(*T.LINE_KEYS, hilbert_udf(_BITS)(F.array(*_lattice_cells())).alias("hkey"))


_H_EVENTS = hilbert_sql(_EVENT_CELL[0], _EVENT_CELL[1], 10, f"({_EVENT_PTS})", "x, y")


@case("hilbert_pack", f"WITH k AS (SELECT x, y, hkey AS key FROM ({_H_EVENTS})), c AS ({_CUTS}) SELECT {_SUMMARY} FROM (SELECT x, y, CAST((SELECT count(*) FROM c WHERE cut < key) AS INTEGER) AS part_id FROM k) GROUP BY part_id")
def hilbert_pack(spark, sf_dir):
    df = T.points(spark, sf_dir, "events")
    return _by_part(router.route(df, curve_runs_of(df, 20, "hilbert", 10)))


def _halved(source: str, levels: int) -> str:
    inner = f"SELECT x, y, min(x) OVER () AS x0, max(x) OVER () AS x9, min(y) OVER () AS y0, max(y) OVER () AS y9, 0 AS cell FROM ({source})"
    for _ in range(levels):
        mid = f"SELECT *, (x0 + x9) / 2 AS mx, (y0 + y9) / 2 AS my FROM ({inner})"
        inner = f"SELECT x, y, CASE WHEN x <= mx THEN x0 ELSE mx END AS x0, CASE WHEN x <= mx THEN mx ELSE x9 END AS x9, CASE WHEN y <= my THEN y0 ELSE my END AS y0, CASE WHEN y <= my THEN my ELSE y9 END AS y9, cell * 4 + CASE WHEN x <= mx THEN 0 ELSE 2 END + CASE WHEN y <= my THEN 0 ELSE 1 END AS cell FROM ({mid})"
    return inner


@case("quad_depth3", f"SELECT count(*) AS n, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y FROM ({_halved(T.points_sql('events'), 3)}) GROUP BY cell")
def quad_depth3(spark, sf_dir):
    layout = quadrants(*_all_points(spark, sf_dir, "events"), 0, 3)
    return _by_part(router.route(T.points(spark, sf_dir, "events"), layout)).drop("part_id")


@case("uniform_grid", f"""SELECT {_SUMMARY} FROM (SELECT x, y, CAST(list_sum(list_transform(range(1, 5), lambda i: CASE WHEN x0 + (x9 - x0) * i / 5 < x THEN 1 ELSE 0 END)) * 5 + list_sum(list_transform(range(1, 5), lambda i: CASE WHEN y0 + (y9 - y0) * i / 5 < y THEN 1 ELSE 0 END)) AS INTEGER) AS part_id FROM ({_EVENT_PTS})) GROUP BY part_id""")
def uniform_grid(spark, sf_dir):
    return _by_part(router.route(T.points(spark, sf_dir, "events"), uniform(*_all_points(spark, sf_dir, "events"), 25)))


for _d in (3, 4, 5, 9):
    _mix = " + ".join(f"CAST({x} AS BIGINT)" for x in T.diagonal_sql(_d))
    case(f"diagonal_points_d{_d}", f"SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST({_mix} AS DOUBLE) AS total FROM lineitem")(
        lambda spark, sf_dir, d=_d: T.diagonal(spark, sf_dir, d).select(*T.LINE_KEYS, geom.total(geom.cols(_axes(d))).alias("total"))
    )


@case("capacity_spec")
def capacity_spec(spark, sf_dir):
    """The bounds each variant plans for the order lines, sampled by a tenth, with and without a margin."""
    whole = phase1.summarize(T.points(spark, sf_dir, "lineitem")).first()
    rows = []
    for variant in ("plain", "count", "bytes"):
        for h in (0.0, None):
            s = plan_spec(variant, whole["n_rows"] // 10, whole["n_bytes"], 65536, None, headroom=h)
            rows.append((variant, h is None, float(s.least), float(s.most)))
    return spark.createDataFrame(rows, "variant string, headroom boolean, least double, most double")


@case("manifest_fixed_tree", f"SELECT part_id, count(*) AS n_rows, CAST(sum(bytes) AS BIGINT) AS bytes, min(x) AS lo_x, max(x) AS hi_x, min(y) AS lo_y, max(y) AS hi_y, CAST(ceil(sum(bytes) / 65536.0) AS BIGINT) AS blocks FROM ({_ROUTED}) GROUP BY part_id")
def manifest_fixed_tree(spark, sf_dir):
    return quality.manifest(_routed(spark, sf_dir), block=65536)
