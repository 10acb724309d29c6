"""Gap tests against brute force, and the hand-made sets whose pruning is known."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cellcluster import gaptest as g

NINE_A = np.array([(170, 437), (142, 12), (406, 49), (205, 47), (476, 163), (360, 599), (594, 196), (225, 136), (151, 138)])
NINE_B = np.array([(1474, 754), (1496, 1354), (1582, 781), (2008, 978), (1556, 1244), (1941, 1032)])


def test_nine_points_lose_four_by_triangle_and_three_by_angle():
    p = NINE_A[0]
    q = NINE_B[np.square(NINE_B - p).sum(axis=1).argmin()]
    stay, tri, ang = g.prune(NINE_A, NINE_B, p, q, 1000)
    assert (tri, ang, stay.sum()) == (4, 3, 2)
    v = g.alternating_prune(NINE_A, NINE_B, 1000)
    assert not v.yes and v.iterations == 1


def test_pingpong_misses_what_pruning_finds():
    a = np.array([(240, 419), (296, 609), (440, 499), (264, 473), (478, 53), (485, 56), (196, 653), (106, 149), (449, 464)])
    b = np.array([(1448, 701), (1948, 397), (1600, 630), (1544, 573), (1464, 54), (1534, 263)])
    assert not g.pingpong(a, b, 1000).yes
    v = g.alternating_prune(a, b, 1000)
    assert v.yes and v.iterations == 2 and g.brute(a, b, 1000).yes


def test_three_iterations():
    a = np.array([(434, 193), (472, 155), (595, 703), (633, 8), (184, 437), (362, 525), (434, 686), (302, 656), (212, 130)])
    b = np.array([(1594, 374), (1780, 162), (1545, 694), (1656, 425), (2088, 365), (1725, 88)])
    v = g.alternating_prune(a, b, 1000)
    assert v.yes and v.iterations == 3


def test_collinear_point_at_the_edge_of_the_ball_survives():
    a, b = np.array([(0, 0), (1000, 0)]), np.array([(2000, 0)])
    assert g.alternating_prune(a, b, 1000).yes


@st.composite
def cells(draw):
    d = draw(st.integers(2, 4))
    w = int(1000 / math.sqrt(d))
    shift = draw(st.lists(st.integers(-2, 2), min_size=d, max_size=d))
    point = st.lists(st.integers(0, w), min_size=d, max_size=d)
    a, b = (np.array(draw(st.lists(point, min_size=1, max_size=12))) for _ in range(2))
    return a, b + np.array(shift) * w


@settings(max_examples=300, deadline=None)
@given(cells(), st.sampled_from(["first", "random", "nearest_box"]))
def test_exact_tests_agree_with_brute_force(pair, start):
    a, b = pair
    truth = g.brute(a, b, 1000).yes
    for name in g.EXACT:
        if name != "planar_front" or a.shape[1] == 2:
            assert g.TESTS[name](a, b, 1000).yes == truth, name
    for rules in ({"tri"}, {"ang"}, set()):
        assert g.alternating_prune(a, b, 1000, start=start, rules=frozenset(rules)).yes == truth
    assert truth or not g.pingpong(a, b, 1000).yes


@settings(max_examples=150, deadline=None)
@given(cells())
def test_relaxed_tests_stay_in_their_band(pair):
    a, b = pair
    least = math.sqrt(g.min_square(a, b))
    for yes, slack in ((g.delta(a, b, 1000, 100).yes, 100), (g.rho_count(a, b, 1000, 0.1).yes, 100)):
        assert yes or least > 1000
        assert not yes or least <= 1000 + slack + 1e-6


@settings(max_examples=150, deadline=None)
@given(cells())
def test_boxes_and_bounds(pair):
    a, b = pair
    verdict = int(g.box_test(a.min(axis=0), a.max(axis=0), b.min(axis=0), b.max(axis=0), 1000))
    truth = g.brute(a, b, 1000).yes
    assert verdict == 0 or (verdict == 1) == truth
    assert g.alternating_prune(a, b, 1000).iterations <= max(1, g.kappa_bound(a, b, 1000 / math.sqrt(a.shape[1]), 1000)) + 1e-9


@pytest.mark.parametrize("d", [2, 3, 4])
def test_pruned_points_have_no_partner(d):
    rng = np.random.default_rng(d)
    for _ in range(200):
        a, b = rng.integers(0, 500, (10, d)), rng.integers(0, 500, (8, d)) + np.r_[1200, [0] * (d - 1)]
        near = np.square(b - a[0]).sum(axis=1)
        if near.min() > 10**6:
            stay, _, _ = g.prune(a, b, a[0], b[near.argmin()], 1000)
            assert all(np.square(b - x).sum(axis=1).min() > 10**6 for x in a[~stay])
            assert g.maximum_angle(a[0], b[near.argmin()], b, 1000) < math.pi
