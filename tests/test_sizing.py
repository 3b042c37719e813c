import math

import pytest

from evenbox.functions import sizing as z


def reachable(least, most, top):
    ok = [False] * (top + 1)
    for s in range(1, top + 1):
        ok[s] = any(s == k or (s > k and ok[s - k]) for k in range(least, min(most, s) + 1))
    return ok


@pytest.mark.parametrize("most", range(1, 13))
def test_fits_is_reachability(most):
    for least in range(1, most + 1):
        ok = reachable(least, most, 150)
        for s in range(1, 151):
            assert bool(z.fits(s, least, most)) == ok[s], (s, least, most)


def test_worked_sizes():
    assert [bool(z.fits(s, 9, 10)) for s in (14, 31, 62, 9, 27, 28, 63)] == [False, False, False, True, True, True, True]


def test_threshold_is_sufficient():
    for least, most in ((9, 10), (3, 7), (95, 100), (1, 2)):
        start = z.always_fits_from(least, most)
        assert all(z.fits(s, least, most) for s in range(start, start + 3 * most))
    assert math.isinf(z.always_fits_from(5, 5))


def test_witness():
    for s in range(1, 200):
        sizes = z.witness_sizes(s, 9, 10)
        assert bool(sizes) == bool(z.fits(s, 9, 10))
        assert not sizes or (sum(sizes) == s and all(9 <= x <= 10 for x in sizes))


@pytest.mark.parametrize(("total", "least", "most"), [(28, 9, 10), (63, 9, 10), (31, 9, 10), (900, 95, 100), (40, 5, 5), (100, 1, 3)])
def test_cut_ranges_are_the_valid_cuts(total, least, most):
    want = {k for k in range(1, total) if z.fits(k, least, most) and z.fits(total - k, least, most)}
    got = {k for a, b in z.cut_ranges(total, least, most) for k in range(math.ceil(a), math.floor(b) + 1) if 0 < k < total}
    assert got == want


def test_worked_ranges():
    assert z.cut_ranges(28, 9, 10) == [(9, 10), (18, 19)]
    assert z.cut_ranges(1000, 450, 550) == [(450, 550)]


def test_sample_of_the_worked_example():
    points, size = z.sample_needed(0.95, 128 << 20, 0.01, 16)
    assert 20e6 < size < 30e6 and points * 16 == size
