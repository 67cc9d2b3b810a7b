"""Hand-computed values and invariants of the learners and selectors."""

import numpy as np
import pytest

from fuzzyfeat.operators.fcm import Centroids, memberships_block, sqdist_block
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.learners.svm import KernelSVM
from fuzzyfeat.operators.learners.tree import AdaBoostM1, Bagging, C45Tree, NBTree, upper_error
from fuzzyfeat.operators.selection import exhaustive, genetic, merit


def frame(x, cat=None):
    x = np.asarray(x, float)
    cat = np.zeros((len(x), 0), np.int64) if cat is None else np.asarray(cat)
    return Frame(x, cat, [f"x{i}" for i in range(x.shape[1])], [f"c{i}" for i in range(cat.shape[1])])


def xor_rows(n=400, seed=1):
    g = np.random.default_rng(seed)
    x = g.random((n, 2))
    return frame(x), ((x[:, 0] > 0.5) != (x[:, 1] > 0.5)).astype(int)


def test_memberships_by_hand():
    assert np.allclose(memberships_block(np.array([[1.0, 4.0]]), 2), [[0.8, 0.2]])
    assert np.allclose(memberships_block(np.array([[1.0, 4.0]]), 3), [[2 / 3, 1 / 3]])
    assert np.allclose(memberships_block(np.array([[0.0, 4.0], [0.0, 0.0]]), 3), [[1, 0], [0.5, 0.5]])
    near_crisp = memberships_block(np.array([[1.0, 1.2, 3.0]]), 1.01)
    assert near_crisp.argmax() == 0 and near_crisp.max() > 0.99


def test_mixed_distance_by_hand():
    v = Centroids(np.array([[0.6, 5 / 6]]), np.array([[1]]))
    d = sqdist_block(np.array([[0.2, 2 / 6]]), np.array([[0]]), v, np.array([0.5, 1.0]), np.array([0.25]))
    assert d[0, 0] == pytest.approx(0.58)


@pytest.mark.parametrize(("rule", "expected"), [("both", [1.0, 0.0]), ("either", [1.0, 1.0])])
def test_unknown_rules(rule, expected):
    v = Centroids(np.array([[np.nan], [0.5]]), np.zeros((2, 0), np.int64))
    d = sqdist_block(np.array([[np.nan]]), np.zeros((1, 0), np.int64), v, np.array([1.0]), np.zeros(0), rule)
    assert np.allclose(d[0], expected)


def test_scaling_all_gains_changes_no_membership():
    g = np.random.default_rng(2)
    x, v = g.random((50, 3)), Centroids(g.random((4, 3)), np.zeros((4, 0), np.int64))
    a, b = (memberships_block(sqdist_block(x, np.zeros((50, 0), np.int64), v, np.array([0.2, 0.5, 0.1]) * f, np.zeros(0)), 3) for f in (1, 7))
    assert np.allclose(a, b) and np.allclose(a.sum(axis=1), 1)


def test_pruning_bound():
    assert upper_error(0, 6, 0.2) == pytest.approx(0.2353, abs=1e-4)


def test_merit_and_searches():
    to_class, mutual = np.array([0.6, 0.4]), np.array([[1, 0.2], [0.2, 1]])
    assert merit([0, 1], to_class, mutual) == pytest.approx(0.6455, abs=1e-4)
    assert merit([], to_class, mutual) == 0
    g = np.random.default_rng(0)
    a, m = g.random(7), g.random((7, 7))
    m = (m + m.T) / 2
    assert genetic(a, m, generations=60)[1] == pytest.approx(exhaustive(a, m)[1], rel=0.02)


def test_tree_learns_levels_and_unknowns():
    g = np.random.default_rng(3)
    c = g.integers(0, 3, 300)
    y = (c == 1).astype(int)
    x = np.where(g.random((300, 1)) < 0.1, np.nan, g.random((300, 1)))
    tree = C45Tree().fit(frame(x, c[:, None]), y, 2)
    assert (tree.predict(frame(x, c[:, None])) == y).all()
    assert np.allclose(tree.distribution(frame(x, np.full((300, 1), -1))).sum(axis=1), 1)


def test_ensembles_beat_one_shallow_tree():
    f, y = xor_rows()
    one = (C45Tree(max_depth=1).fit(f, y, 2).predict(f) == y).mean()
    assert (AdaBoostM1(10).fit(f, y, 2).predict(f) == y).mean() >= one
    assert (Bagging(5).fit(f, y, 2).predict(f) == y).mean() > 0.9
    assert (NBTree().fit(f, y, 2).predict(f) == y).mean() >= one


def test_explicit_map_is_the_kernel():
    g = np.random.default_rng(4)
    a, b = g.random((20, 4)), g.random((15, 4))
    for homogeneous in (False, True):
        m = KernelSVM("poly", 3, homogeneous=homogeneous)
        assert np.allclose(m.monomials(a) @ m.monomials(b).T, m.gram(a, b))


@pytest.mark.parametrize("approx", ["explicit", "nystrom", "rff"])
def test_kernel_machines_solve_xor(approx):
    f, y = xor_rows()
    model = KernelSVM("poly", 2, approx="explicit", C=100) if approx == "explicit" else KernelSVM("rbf", gamma=10, C=100, approx=approx)
    assert (model.fit(f, y, 2).predict(f) == y).mean() > 0.93


@pytest.mark.parametrize("rule", ["both", "either"])
def test_expanded_rows_serve_all_centroids(rule):
    from fuzzyfeat.operators.fcm import _sums, distances, expanded

    g = np.random.default_rng(6)
    x, s, w = g.random((60, 3)), g.integers(-2, 4, (60, 2)), g.random(60)
    x[g.random(x.shape) < 0.2] = np.nan
    terms, gn, gc = expanded(x), np.array([0.3, 0.5, 0.2]), np.array([0.4, 0.1])
    for k in (1, 4):
        v = Centroids(np.where(g.random((k, 3)) < 0.2, np.nan, g.random((k, 3))), g.integers(-1, 4, (k, 2)))
        lost = lambda a, b: (a and b) if rule == "both" else (a or b)
        one = lambda a, b, no, far: 1.0 if lost(no(a), no(b)) else 0.0 if no(a) or no(b) else far(a, b)
        plain = [[sum(gn[q] * one(x[i, q], v.num[j, q], np.isnan, lambda a, b: (a - b) ** 2) for q in range(3)) + sum(gc[q] * one(s[i, q], v.cat[j, q], lambda a: a == -1, lambda a, b: float(a != b)) for q in range(2)) for j in range(k)] for i in range(60)]
        assert np.allclose(distances(terms, s, v, gn, gc, rule), plain) and np.allclose(sqdist_block(x, s, v, gn, gc, rule), plain)
        u = memberships_block(np.array(plain), 3.0) ** 3 * w[:, None]
        total = _sums(terms, s, w, v, gn, gc, 3.0, rule, [4, 100])  # few levels and many
        assert np.allclose(total[:, :3], u.T @ np.nan_to_num(x)) and np.allclose(total[:, 6:10], [[u[s[:, 0] == c, j].sum() for c in range(4)] for j in range(k)])
        assert np.allclose(total[:, 10:14], [[u[s[:, 1] == c, j].sum() for c in range(4)] for j in range(k)]) and np.allclose(total[:, -1], (u * plain).sum(axis=0))
