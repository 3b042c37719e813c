"""Learn a layout of any method from a table: sample, histogram, boundaries."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.functions.curves import curve_bits
from evenbox.functions.sizing import ceil_div
from evenbox.operators import phase1
from evenbox.plans import baselines
from evenbox.plans.cut import Counters
from evenbox.plans.grow import Layout, Tree, default_headroom, grow, grow_top, plan_spec
from evenbox.plans.rstar_insert import rstar_insert
from evenbox.sources.tables import MODULUS

METHODS = ("mbs_plain", "mbs_count", "mbs_bytes", "str", "kd", "z", "hilbert", "quad", "grid", "rstar_insert")


@dataclass
class Learned:
    layout: Layout | baselines.CurveLayout
    method: str
    points: int
    #: of the boundaries alone
    seconds: float
    #: of every phase before routing, by name
    phases: dict[str, float] = field(default_factory=dict)


def learn(df: DataFrame, method: str, block: int, axes: Sequence[str] = ("x", "y"), ratio: float = 1.0, alpha: float = 0.95, rho: float = 0.4, headroom: float | None = None, capacity: str = "block", orphans: str = "nearest", seed: int = 0, cost: str = "area", grid: Sequence[int] | None = None) -> Learned:
    """Sample ``df`` (axes, bytes, kh) and grow the boundaries on the driver.

    headroom lowers the aimed size of every method alike; None is the default margin, 0 the plain setting. Splits by count and the
    baselines of a sample that is more than the driver should grow (``DRIVER_VALUES``) go on in tasks.
    """
    marks = [time.perf_counter()]
    good = df.where(phase1.valid(axes))
    row = phase1.summarize(good, axes).first()
    data, d = row["n_bytes"] or 0, len(axes)
    if method in ("mbs_plain", "mbs_count") and row["n_rows"] * min(ratio, 1.0) * (d + 1) > DRIVER_VALUES:
        done = learn_distributed(df, block, axes, ratio, method.removeprefix("mbs_"), alpha, rho, headroom, max(1, TASK_VALUES // (d + 1)), max(1, TOP_VALUES // (d + 1)), seed, cost, (row["n_rows"], data))
        done.phases["summary"] += time.perf_counter() - marks[0] - sum(done.phases.values())
        return done
    if method in BASELINES and row["n_rows"] * min(ratio, 1.0) * (d + 1) > DRIVER_VALUES:
        return _baseline_distributed(good, method, block, axes, ratio, headroom, seed, data, marks)
    marks.append(time.perf_counter())
    sample = phase1.sample_by_hash(good, ratio, seed)
    weights = None
    if method == "mbs_bytes":
        low, high = [row[f"min_{a}"] for a in axes], [row[f"max_{a}"] for a in axes]
        n = sample.count()
        grid = list(grid or phase1.default_grid(n, d))
        histogram = phase1.byte_histogram(good, low, high, grid, axes)
        sample = phase1.weigh(sample.select(*axes, "kh"), histogram, phase1.cell_number(low, high, grid, axes), orphans, grid)
    points, hashes, weights = phase1.to_numpy(sample, axes, "w" if method == "mbs_bytes" else None)
    n = len(points)
    marks.append(time.perf_counter())
    if headroom is None:
        headroom = default_headroom(n, data, block)
    aimed = max(1, int(block * (1 - headroom)))
    parts, each = max(1, ceil_div(data, aimed)), max(1, ceil_div(n * aimed, max(data, 1)))
    if not n:
        layout = Layout(method, Tree(), {0: ([], [])}, {0: 0.0}, {0: 0}, Counters())
    elif method.startswith("mbs_"):
        spec = plan_spec(method.removeprefix("mbs_"), n, data, block, None if weights is None else float(weights.sum()), alpha, rho, headroom, capacity, cost)
        layout = grow(points, hashes, spec, weights, method=method)
    elif method == "str":
        layout = baselines.slabs(points, hashes, parts)
    elif method == "kd":
        layout = baselines.medians(points, hashes, parts)
    elif method in ("z", "hilbert"):
        layout = baselines.curve_runs(points, parts, method)
    elif method == "quad":
        layout = baselines.quadrants(points, hashes, each)
    elif method == "grid":
        layout = baselines.uniform(points, hashes, parts)
    elif method == "rstar_insert":
        most = max(2, each)
        layout = rstar_insert(points, max(1, int(0.3 * most)), most)
    else:
        raise ValueError(f"no method {method}")
    marks.append(time.perf_counter())
    phases = {name: b - a for name, a, b in zip(("summary", "sample", "boundaries"), marks, marks[1:], strict=False)}
    return Learned(layout, method, n, phases["boundaries"], phases)


#: sample points that one task finishes, and that the driver grows the first levels from
TASK_POINTS = 1_000_000
TOP_POINTS = 200_000
#: coordinates and hashes of a sample that ``learn`` grows on the driver, of those one task then finishes, and of the thin sample
#: for the first levels; growing holds some forty times as much
DRIVER_VALUES = 1_000_000
TASK_VALUES = 1_500_000
TOP_VALUES = 600_000


def learn_distributed(df: DataFrame, block: int, axes: Sequence[str] = ("x", "y"), ratio: float = 1.0, variant: str = "count", alpha: float = 0.95, rho: float = 0.4, headroom: float | None = None, task_points: int = TASK_POINTS, top_points: int = TOP_POINTS, seed: int = 0, cost: str = "area", known: tuple[int, int] | None = None) -> Learned:
    """A layout from a sample larger than one machine takes: the driver grows the first levels from a thin sample, each subtree of
    the full sample is finished in a task of its own, and the subtrees are hung below the first levels. ``known``: records and bytes
    with valid axes, where the caller has counted them. The sample is made once and kept on the executors' disks meanwhile.

    What comes back to the driver is a row for each subtree with the cuts and boxes of its partitions. With variant "bytes" a
    sample record weighs its own bytes, scaled to those of the whole table. Every subtree is repaired to a tileable size by itself.
    """
    marks = [time.perf_counter()]
    good = df.where(phase1.valid(axes))
    total = (known or good.agg(F.count("*"), F.coalesce(F.sum("bytes"), F.lit(0))).first())[1]
    marks.append(time.perf_counter())
    sample = phase1.sample_by_hash(good, ratio, seed).select(*[F.col(c).cast("double").alias(c) for c in (*axes, "kh", "bytes")]).persist(StorageLevel.DISK_ONLY)
    thin_headroom = headroom
    try:
        n, held = sample.agg(F.count("*"), F.coalesce(F.sum("bytes"), F.lit(0))).first()
        if not n:
            return learn(df, f"mbs_{variant}", block, axes, ratio, alpha, rho, headroom)
        if headroom is None:
            headroom = default_headroom(n, total, block)
        spec = plan_spec(variant, n, total, block, float(total) if variant == "bytes" else None, alpha, rho, headroom, cost=cost)
        leaves = max(1, ceil_div(n, task_points))
        top = None
        if leaves > 1:
            # a hash of its own: rows that one turn of the key hash takes can have none in common with another turn's
            drawn = F.pmod(F.xxhash64(*axes, "kh", F.lit(seed)), F.lit(MODULUS)) < int(min(1.0, top_points / n) * MODULUS)
            points, hashes, _ = phase1.to_numpy(sample.where(drawn), axes)
            thin = plan_spec("count" if variant == "count" else "plain", len(points), total, block, None, alpha, rho, thin_headroom, cost=cost)
            top = grow_top(points, hashes, thin, None, max(len(points) / leaves, thin.most)) if len(points) > 1 else None
        marks.append(time.perf_counter())
        grown = _subtrees(sample, axes, top, spec, total / max(held, 1))
    finally:
        sample.unpersist()
    layout = _hung(top.tree if top else Tree(), grown, len(axes), spec, f"mbs_{variant}")
    for times in ([list(vars(top.counters).values())] if top else []) + [r["times"] for r in grown.values()]:
        layout.counters = Counters(*[a + b for a, b in zip(vars(layout.counters).values(), times, strict=True)])
    marks.append(time.perf_counter())
    phases = {name: b - a for name, a, b in zip(("summary", "sample", "boundaries"), marks, marks[1:], strict=False)}
    return Learned(layout, f"mbs_{variant}", n, phases["boundaries"], phases)


def _subtrees(sample: DataFrame, axes: Sequence[str], top: Layout | None, spec, scale: float) -> dict:
    """A row for each leaf of ``top`` that has sample points: the tree and the boxes grown from them, in a task of its own."""
    from evenbox.operators.router import route_points

    routed = route_points(sample, top.tree, axes, "arrow") if top else sample.withColumn("part_id", F.lit(0))
    return _finished(routed, len(top.tree.axis) + 1 if top else 1, [*axes, "kh", "bytes"], lambda points, hashes, held: grow(points, hashes, spec, held * scale if spec.variant == "bytes" else None))


def _finished(routed: DataFrame, parts: int, columns: Sequence[str], build: Callable[[np.ndarray, np.ndarray, np.ndarray], Layout]) -> dict:
    """A row for each part_id below ``parts`` that has records: the layout that ``build`` makes of their axes, hashes and bytes (the
    last two of ``columns``), in a task of its own."""
    floats, d = pa.list_(pa.list_(pa.float64())), len(columns) - 2
    kinds = {"subtree": pa.int32(), "axis": pa.list_(pa.int32()), "cut": floats, "lo": pa.list_(pa.int32()), "hi": pa.list_(pa.int32()), "n": pa.list_(pa.int64()), "w": pa.list_(pa.float64()), "blo": floats, "bhi": floats, "times": pa.list_(pa.int64())}

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.column_stack([batch.column(c).to_numpy() for c in ("part_id", *columns)]) for batch in batches]
        rows = np.concatenate(held) if held else np.zeros((0, len(columns) + 1))
        held.clear()
        for subtree in np.unique(rows[:, 0]):
            data = rows[rows[:, 0] == subtree, 1:]
            data = data[np.lexsort(data.T[::-1])]
            layout = build(data[:, :d].copy(), data[:, d].copy(), data[:, -1])
            tree, ids = layout.tree, sorted(layout.boxes)
            out = {"subtree": int(subtree), "axis": tree.axis, "cut": tree.cut, "lo": tree.lo, "hi": tree.hi, "n": [layout.counts[i] for i in ids], "w": [float(layout.weights[i]) for i in ids], "blo": [layout.boxes[i][0] for i in ids], "bhi": [layout.boxes[i][1] for i in ids], "times": list(vars(layout.counters).values())}
            yield pa.RecordBatch.from_pylist([out], pa.schema(list(kinds.items())))

    dealt = routed.repartitionById(parts, "part_id")  # hashing would put several in one task
    schema = "subtree int, axis array<int>, cut array<array<double>>, lo array<int>, hi array<int>, n array<long>, w array<double>, blo array<array<double>>, bhi array<array<double>>, times array<long>"
    return {r["subtree"]: r for r in dealt.mapInArrow(finish, schema).collect()}


def _hung(top: Tree, grown: dict, d: int, spec, method: str) -> Layout:
    """One tree of the first levels and the subtrees that stand in place of their leaves."""
    tree = Tree([*top.axis], [*top.cut], [*top.lo], [*top.hi])
    boxes, weights, counts, roots = {}, {}, {}, {}
    for leaf in range(len(top.axis) + 1):
        row, node, base = grown.get(leaf), len(tree.axis), len(boxes)
        if row is None:  # no sample point came here
            boxes[base], weights[base], counts[base], roots[leaf] = ([0.0] * d, [0.0] * d), 0.0, 0, -(base + 1)
            continue
        child = lambda c, node=node, base=base: c + node if c >= 0 else c - base
        tree.axis += row["axis"]
        tree.cut += [list(c) for c in row["cut"]]
        tree.lo += [child(c) for c in row["lo"]]
        tree.hi += [child(c) for c in row["hi"]]
        for i, (n, w, lo, hi) in enumerate(zip(row["n"], row["w"], row["blo"], row["bhi"], strict=True)):
            boxes[base + i], weights[base + i], counts[base + i] = (list(lo), list(hi)), w, n
        roots[leaf] = node if row["axis"] else -(base + 1)
    for side in (tree.lo, tree.hi):
        for i in range(len(top.axis)):
            side[i] = roots[-side[i] - 1] if side[i] < 0 else side[i]
    return Layout(method, tree, boxes, weights, counts, Counters(), spec)


#: methods without weights or repairs: equal shares by rank, or equal cells
BASELINES = ("str", "kd", "z", "hilbert", "grid")
#: coordinates and hashes that one task cuts into slabs or at medians; that holds some six times as much
SHARE_VALUES = 6_000_000


def _baseline_distributed(good: DataFrame, method: str, block: int, axes: Sequence[str], ratio: float, headroom: float | None, seed: int, data: int, marks: list[float]) -> Learned:
    """The layout that ``learn`` makes of the same sample on the driver, with the points left on the executors: cuts are found by rank
    in a sort, until what lies between them is for one task. The driver gets the cuts, and a box for each partition."""
    marks.append(time.perf_counter())
    d = len(axes)
    sample = phase1.sample_by_hash(good, ratio, seed).select(*[F.col(c).cast("double").alias(c) for c in (*axes, "kh")]).persist(StorageLevel.DISK_ONLY)
    try:
        row = phase1.summarize(sample.withColumn("bytes", F.lit(0)), axes).first()
        n = row["n_rows"]
        if not n:
            return Learned(Layout(method, Tree(), {0: ([], [])}, {0: 0.0}, {0: 0}, Counters()), method, 0, 0.0)
        marks.append(time.perf_counter())
        if headroom is None:
            headroom = default_headroom(n, data, block)
        parts = max(1, ceil_div(data, max(1, int(block * (1 - headroom)))))
        if method in ("z", "hilbert"):
            layout = curve_runs_of(sample.withColumn("bytes", F.lit(0)), parts, method, axes=axes)
        elif method == "grid":
            layout = _boxed(sample, axes, baselines.cells(np.array([row[f"min_{a}"] for a in axes]), np.array([row[f"max_{a}"] for a in axes]), parts))
        else:
            layout = _shares(sample, axes, method, parts, n)
    finally:
        sample.unpersist()
    marks.append(time.perf_counter())
    phases = {name: b - a for name, a, b in zip(("summary", "sample", "boundaries"), marks, marks[1:], strict=False)}
    return Learned(layout, method, n, phases["boundaries"], phases)


def _boxed(sample: DataFrame, axes: Sequence[str], tree: Tree) -> Layout:
    """The grid of a tree with the boxes and counts of the sample points in its cells."""
    from evenbox.operators.router import route_points

    ends = [F.array(*[f(a) for a in axes]).alias(f.__name__) for f in (F.min, F.max)]
    held = {r["part_id"]: r for r in route_points(sample, tree, axes, "arrow").groupBy("part_id").agg(F.count("*").alias("n"), *ends).collect()}
    ids = range(len(tree.axis) + 1)
    boxes = {i: (list(held[i]["min"]), list(held[i]["max"])) if i in held else ([], []) for i in ids}
    counts = {i: held[i]["n"] if i in held else 0 for i in ids}
    return Layout("grid", tree, boxes, {i: float(k) for i, k in counts.items()}, counts, Counters())


def _shares(sample: DataFrame, axes: Sequence[str], method: str, parts: int, n: int) -> Layout:
    """Slabs or medians. Level by level all groups are cut at once, where the ranks of their points say; groups that are small enough
    are finished in tasks."""
    d = len(axes)
    f = baselines.fan_out(parts, d) if method == "str" else 2
    levels = d if method == "str" else baselines.median_depth(parts)
    edges_of = (lambda k: baselines.slab_edges(k, f)) if method == "str" else (lambda k: [0, (k + 1) // 2, k])
    sizes, level, cuts = [n], 0, []
    grouped, kept = sample.withColumn("part_id", F.lit(0)), []
    try:
        while level < levels and max(sizes) * (d + 1) > SHARE_VALUES and min(sizes) >= f:
            axis = level % d
            edges = [edges_of(k) for k in sizes]
            columns = [*[axes[(axis + j) % d] for j in range(d)], "kh"]
            found, moved = _cut_by_rank(grouped, columns, edges, kept)
            cuts.append((axis, found))
            sizes = [b - a for own in edges for a, b in zip(own, own[1:], strict=False)]
            grouped, level = moved, level + 1
        build = baselines.slabs if method == "str" else baselines.medians
        columns = [*axes, "kh", "kh"]
        grown = _finished(grouped, len(sizes), columns, lambda points, hashes, _, level=level: build(points, hashes, parts, level=level))
    finally:
        for frame in kept:
            frame.unpersist()
    top, children = Tree(), [-(i + 1) for i in range(len(sizes))]
    for axis, found in reversed(cuts):
        fan = len(children) // len(found)
        children = [baselines._binary(top, axis, own, children[i * fan : (i + 1) * fan]) for i, own in enumerate(found)]
    layout = _hung(baselines._rooted(top), grown, d, None, method)
    layout.tree = baselines._rooted(layout.tree)
    return layout


def _cut_by_rank(grouped: DataFrame, columns: Sequence[str], edges: list[list[int]], kept: list[DataFrame]) -> tuple[list[list[list[float]]], DataFrame]:
    """Of groups 0.. (part_id), sorted by ``columns``: the keys of the last row before each inner edge, by group, and the rows with the
    number of their piece as part_id, in the order of groups and edges. The sorted rows stay on disk, in ``kept``."""
    ordered = grouped.orderBy("part_id", *columns).withColumn("_task", F.spark_partition_id()).persist(StorageLevel.DISK_ONLY)
    kept.append(ordered)
    begins: dict[int, dict[int, int]] = {}
    before = dict.fromkeys(range(len(edges)), 0)
    for r in sorted(ordered.groupBy("_task", "part_id").count().collect()):
        begins.setdefault(r["_task"], {})[r["part_id"]] = before[r["part_id"]]
        before[r["part_id"]] += r["count"]
    first = np.cumsum([0, *[len(own) - 1 for own in edges]])

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Adds each row's rank in its group, from 1, and its piece."""
        seen: dict[int, int] = {}
        for batch in batches:
            group, task = batch.column("part_id").to_numpy(), batch.column("_task").to_numpy()
            rank, piece = np.zeros(len(group), np.int64), np.zeros(len(group), np.int32)
            for g in np.unique(group).tolist():
                at = np.flatnonzero(group == g)
                begin = seen.setdefault(g, begins[int(task[0])][g])
                rank[at] = begin + 1 + np.arange(len(at))
                piece[at] = first[g] + np.searchsorted(edges[g][1:], rank[at], "left")
                seen[g] += len(at)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rank), pa.array(piece)], [*batch.schema.names, "_rank", "_piece"])

    def last(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in place(batches):
            group, rank, piece = (batch.column(c).to_numpy() for c in ("part_id", "_rank", "_piece"))
            ends = np.array([e for own in edges for e in own[1:]])
            yield batch.filter(pa.array(rank == ends[piece])).select(["part_id", "_piece", *columns])

    kinds = ", ".join(f"{c} double" for c in columns)
    ends = ordered.mapInArrow(last, f"part_id int, _piece int, {kinds}").toArrow().sort_by("_piece").to_pylist()
    found: list[list[list[float]]] = [[] for _ in edges]
    for r in ends:
        if r["_piece"] + 1 < first[r["part_id"] + 1]:
            found[r["part_id"]].append([r[c] for c in columns])
    moved = ordered.mapInArrow(place, f"{', '.join(f'`{c}` {t}' for c, t in ordered.dtypes)}, _rank long, _piece int").withColumn("part_id", F.col("_piece")).drop("_task", "_rank", "_piece")
    return found, moved


def runs_of(sample: DataFrame, parts: int, axes: Sequence[str] = ("x", "y")) -> Tree:
    """The tree of ``baselines.runs`` of a sample that stays on the executors."""
    kept: list[DataFrame] = []
    grouped = sample.where(phase1.valid(axes)).select(*[F.col(c).cast("double").alias(c) for c in (*axes, "kh")]).withColumn("part_id", F.lit(0))
    n, tree = grouped.count(), Tree()
    parts = max(1, min(parts, n))
    try:
        cuts = _cut_by_rank(grouped, [*axes, "kh"], [baselines.slab_edges(n, parts)], kept)[0][0]
    finally:
        for frame in kept:
            frame.unpersist()
    baselines._binary(tree, 0, cuts, [-(i + 1) for i in range(parts)])
    return baselines._rooted(tree)


def curve_runs_of(df: DataFrame, parts: int, method: str = "z", bits: int | None = None, axes: Sequence[str] = ("x", "y")) -> baselines.CurveLayout:
    """``baselines.curve_runs`` of a whole table: the keys at the cuts' ranks, exactly, without bringing the points to the driver.

    The keys are sorted on the executors; the driver gets those at the cuts.
    """
    good = df.where(phase1.valid(axes))
    row = phase1.summarize(good, axes).first()
    n, d = row["n_rows"], len(axes)
    bits = bits or curve_bits(d)
    layout = baselines.CurveLayout(method, [float(row[f"min_{a}"] or 0.0) for a in axes], [float(row[f"max_{a}"] or 0.0) for a in axes], bits, [])
    sought = np.array(sorted({r for i in range(1, parts) if (r := n * i // parts)}), np.int64)
    if not len(sought):
        return layout

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(layout.keys(np.column_stack([c.to_numpy() for c in batch.columns])))], ["key"])

    keys = good.select(*[F.col(a).cast("double") for a in axes]).mapInArrow(keyed, "key long").orderBy("key").withColumn("_task", F.spark_partition_id()).persist(StorageLevel.DISK_ONLY)
    try:
        held = sorted(map(tuple, keys.groupBy("_task").count().collect()))
        begins = dict(zip([t for t, _ in held], np.cumsum([0, *[k for _, k in held]]).tolist(), strict=False))

        def picked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            below = None
            for batch in batches:
                if not batch.num_rows:
                    continue
                if below is None:
                    below = begins[batch.column("_task")[0].as_py()]
                own = sought[(sought > below) & (sought <= below + batch.num_rows)] - below - 1
                below += batch.num_rows
                yield batch.select(["key"]).take(pa.array(own))

        layout.cuts = sorted(set(keys.mapInArrow(picked, "key long").toArrow()["key"].to_pylist()))
    finally:
        keys.unpersist()
    return layout
