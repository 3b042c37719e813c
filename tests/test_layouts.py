import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from evenbox.functions.sizing import cut_ranges, fits
from evenbox.plans.baselines import curve_runs, fan_out, medians, quadrants, slabs, uniform
from evenbox.plans.cut import Counters, Node, Spec, allowed, axis_order, choose_cut, correct_weights, margins, sweep
from evenbox.plans.grow import grow, plan_spec
from evenbox.plans.rstar_insert import rstar_insert


def cloud(n, d=2, seed=0, coincident=False):
    random = np.random.default_rng(seed)
    points = random.random((n, d))
    if coincident:
        points[: n // 2] = points[0]
    return points, random.random(n)


def test_correction_worked_example():
    moved, hits = correct_weights(np.full(5, 200.0), cut_ranges(1000, 450, 550))
    assert hits == 1 and moved.tolist() == [200, 200, 100, 300, 200]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.floats(1, 400), min_size=2, max_size=30), st.floats(50, 300))
def test_correction_keeps_weight(weights, most):
    weights = np.array(weights)
    ranges = cut_ranges(weights.sum(), 0.95 * most, most)
    moved, hits = correct_weights(weights, ranges)
    assert abs(moved.sum() - weights.sum()) < 1e-6 * weights.sum() and (moved > 0).all()
    if hits:
        at = np.cumsum(moved)
        assert any(a - 1e-6 <= p <= b + 1e-6 for a, b in ranges for p in at)


def test_cut_against_brute_force():
    for seed in range(20):
        points, hashes = cloud(30, seed=seed)
        node = Node(np.arange(30), points, points, hashes, np.ones(30))
        axis, order, k, _ = choose_cut(node, Spec("plain", 3, 10, 0.0), Counters())
        costs = {}
        for a in (0, 1):
            o = axis_order(points, hashes, a)
            for j in range(3, 28):
                sides = [points[o[:j]], points[o[j:]]]
                ext = [s.max(axis=0) - s.min(axis=0) for s in sides]
                costs[a, j] = (sum(e.prod() for e in ext), sum(e.sum() for e in ext))
        best_axis = min((0, 1), key=lambda a: sum(costs[a, j][1] for j in range(3, 28)))
        assert axis == best_axis
        assert costs[axis, k][0] == pytest.approx(min(costs[axis, j][0] for j in range(3, 28)))


@pytest.mark.parametrize("variant", ["count", "bytes"])
@pytest.mark.parametrize("coincident", [False, True])
def test_leaves_in_bounds(variant, coincident):
    points, hashes = cloud(1500, seed=4, coincident=coincident)
    spec = Spec(variant, 45.0, 50.0) if variant == "bytes" else Spec("count", 45, 50)
    weights = np.random.default_rng(2).exponential(1.0, 1500) if variant == "bytes" else None
    if weights is not None:
        weights *= 1500 / weights.sum()
    layout = grow(points, hashes, spec, weights)
    sizes = layout.weights if variant == "bytes" else layout.counts
    assert all(layout.spec.least - 1e-6 <= s <= layout.spec.most + 1e-6 for s in sizes.values())
    assert sum(layout.counts.values()) == 1500


def test_window_without_a_valid_cut():
    for n in (285, 290, 300):
        points, hashes = cloud(n, seed=n)
        layout = grow(points, hashes, Spec("count", 95, 100))
        assert sorted(layout.counts.values())[0] >= 95 and layout.counters.relaxed > 0


def test_routing_reproduces_leaves():
    points, hashes = cloud(800, 3, seed=9, coincident=True)
    for layout in (grow(points, hashes, Spec("count", 30, 33)), slabs(points, hashes, 27), medians(points, hashes, 16), quadrants(points, hashes, 60), uniform(points, hashes, 27)):
        counts = np.bincount(layout.tree.route(points, hashes), minlength=layout.parts)
        assert counts.tolist() == [layout.counts[i] for i in range(layout.parts)], layout.method


def test_layout_ignores_row_order_of_equal_work():
    points, hashes = cloud(400, seed=5)
    turn = np.random.default_rng(1).permutation(400)
    a, b = grow(points, hashes, Spec("count", 19, 21)), grow(points[turn], hashes[turn], Spec("count", 19, 21))
    assert sorted(map(str, a.boxes.values())) == sorted(map(str, b.boxes.values()))


def test_small_and_heavy_nodes():
    points, hashes = cloud(1)
    assert grow(points, hashes, Spec("bytes", 0.5, 1.0), np.array([5.0])).counters.oversize == 1
    layout = grow(*cloud(3), Spec("bytes", 9.0, 10.0), np.array([1.0, 50.0, 1.0]))
    assert sum(layout.counts.values()) == 3


def test_fan_out():
    assert [fan_out(800, d) ** d for d in (2, 3, 4, 5, 7, 9)] == [841, 1000, 1296, 1024, 2187, 19683]


def test_curves_are_bijections_on_small_grids():
    grid = np.array([[x, y] for x in range(16) for y in range(16)], float)
    for method in ("z", "hilbert"):
        layout = curve_runs(grid, 4, method, 4)
        keys = layout.keys(grid)
        assert sorted(keys.tolist()) == list(range(256))
        if method == "hilbert":
            cells = layout.cells(grid)[np.argsort(keys)]
            assert (np.abs(np.diff(cells, axis=0)).sum(axis=1) == 1).all()


def test_insert_tree_bounds():
    points, _ = cloud(500, seed=7)
    layout = rstar_insert(points, 6, 20)
    assert sum(layout.counts.values()) == 500 and all(6 <= n <= 20 for n in layout.counts.values())


def test_weighted_sides_fit():
    points, hashes = cloud(100, seed=3)
    spec = plan_spec("bytes", 100, 100_000, 10_000)
    weights = np.full(100, 1000.0)
    node = Node(np.arange(100), points, points, hashes, weights)
    ok = allowed(node, axis_order(points, hashes, 0), spec)
    k = np.flatnonzero(ok) + 1
    assert all(fits(1000.0 * i, spec.least, spec.most) and fits(1000.0 * (100 - i), spec.least, spec.most) for i in k)
    assert sweep(points, axis_order(points, hashes, 0)).area.shape == (99,)


@pytest.mark.parametrize("d", [2, 7, 9])
def test_orders_handed_down_and_margins_of_a_window(d):
    """As sorting again and as the whole sweep, exact copies included."""
    points, hashes = cloud(300, d, coincident=True)
    hashes[100:140] = hashes[100]
    node = Node(np.arange(300), points, points, hashes, np.ones(300))
    order = node.order(1)
    assert (margins(points, order, 120, 180) == sweep(points, order).margin[119:180]).all()
    for half in node.halves(order, 130, np.ones(300)):
        assert all((half.order(a) == axis_order(half.raw, half.hashes, a)).all() for a in range(d))
