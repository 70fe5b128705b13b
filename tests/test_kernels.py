import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from multiscale_scatter.operators import kdtree, kernels
from multiscale_scatter.operators.layout import LayoutPlan, _Borders

points = st.lists(st.tuples(st.integers(0, 40), st.integers(0, 40)), min_size=0, max_size=80)


@settings(max_examples=80, deadline=None)
@given(points, st.sampled_from([0.0, 0.5, 1.0, 1.7, 3.0]))
def test_placers_agree(ps, theta):
    u, v = (np.array([p[k] for p in ps], float) / 8 for k in (0, 1))
    scan = kernels.place_with_scan(u, v, theta)
    assert (kernels.place_with_grid(u, v, theta) == scan).all()
    assert (kernels.place_with_tree(u, v, theta) == scan).all()
    kept = np.flatnonzero(scan == np.arange(len(u)))
    for a in kept:
        for b in kept:
            assert a == b or max(abs(u[a] - u[b]), abs(v[a] - v[b])) >= theta
    assert all(scan[i] < i for i in range(len(u)) if scan[i] != i)


def test_split_example():
    """Five marks along a horizontal split, A to E by importance: D goes into A, E into C."""
    names = "BDACE"
    along = np.array([0.0, 1.2, 1.7, 3.2, 3.8])
    across = np.array([0.4, -0.3, 0.5, -0.4, 0.3])
    rank = np.array(["ABCDE".index(n) for n in names])
    into = kernels.sweep_split(along, across, rank, 1.0)
    assert [names[i] for i in into] == ["B", "A", "A", "C", "C"]


def test_nine_objects_three_levels():
    rng = np.random.default_rng(3)
    u, v = rng.random(9) * 8, rng.random(9) * 8
    n = {i: 1 for i in range(9)}
    before = set(range(9))
    for _, child, parent in kernels.place_levels(u, v, 1.5, 3, 2.0):
        new: dict[int, int] = {}
        for c, p in zip(child, parent, strict=True):
            new[p] = new.get(p, 0) + n[c]
        assert sum(new.values()) == 9 and set(new) <= before
        assert all(p <= c for c, p in zip(child, parent, strict=True))
        n, before = new, set(new)


def test_degenerate():
    none = np.zeros(0)
    assert len(kernels.place_with_grid(none, none, 1.0)) == 0
    same = np.zeros(5)
    assert (kernels.place_with_grid(same, same, 1.0) == 0).all()
    assert (kernels.place_with_grid(same, same, 0.0) == np.arange(5)).all()
    pair = np.array([0.0, 1.0])
    assert (kernels.place_with_grid(pair, np.zeros(2), 1.0) == np.arange(2)).all()


@settings(max_examples=40, deadline=None)
@given(points.filter(lambda p: len(p) > 4), st.sampled_from([3, 7, 20]))
def test_repair_leaves_no_pair(ps, most):
    """Placing within leaves and closing the splits leaves no pair too close; without closing there can be some."""
    raw = np.array(ps, float)
    plan = LayoutPlan((0.0, 40.0), (0.0, 40.0), levels=1, top=(500.0, 500.0))
    tree = kdtree.build(raw, most)
    leaf = tree.leaf_of(raw[:, 0], raw[:, 1])
    u, v = raw[:, 0] / 40 * 5, raw[:, 1] / 40 * 5
    stays = np.zeros(len(raw), bool)
    for p in range(tree.leaves):
        rows = np.flatnonzero(leaf == p)
        into = kernels.place_with_grid(u[rows], v[rows], 1.0)
        stays[rows[into == np.arange(len(rows))]] = True
    at = np.flatnonzero(stays)
    into = _Borders(tree, plan, 1).repair(u[at], v[at], leaf[at], at, range(50))
    left = at[into == np.arange(len(at))]
    for a in left:
        for b in left:
            assert a == b or max(abs(u[a] - u[b]), abs(v[a] - v[b])) >= 1.0 - 1e-12


def test_tree_ties():
    column = np.array([[1.0, k] for k in range(10)])
    assert kdtree.build(column, 3).leaves == 4
    stuck = kdtree.build(np.ones((10, 2)), 3)
    assert stuck.leaves == 1
    skew = np.array([[1.0, 0.0]] * 9 + [[2.0, 0.0]])
    tree = kdtree.build(skew, 3)
    assert tree.leaves == 2 and sorted(np.bincount(tree.leaf_of(skew[:, 0], skew[:, 1]))) == [1, 9]


def test_pruning_covers_points():
    rng = np.random.default_rng(5)
    raw = rng.random((500, 2))
    tree = kdtree.build(raw, 20)
    leaf = tree.leaf_of(raw[:, 0], raw[:, 1])
    for _ in range(50):
        x0, y0 = rng.random(2)
        inside = (raw[:, 0] >= x0) & (raw[:, 0] <= x0 + 0.2) & (raw[:, 1] >= y0) & (raw[:, 1] <= y0 + 0.2)
        assert set(leaf[inside]) <= set(tree.leaves_meeting(x0, y0, x0 + 0.2, y0 + 0.2))


def test_hull():
    square = np.array([(0, 0), (2, 0), (2, 2), (0, 2), (1, 1), (1, 0)], float)
    corners = kernels.convex_hull(square)
    assert len(corners) == 4 and kernels.polygon_area(corners) == pytest.approx(4.0)
    assert kernels.polygon_area(kernels.convex_hull(np.array([(0, 0), (1, 1)]))) == 0
