"""Pairs, rectangles, orderings, samples, costs."""

from itertools import combinations

import numpy as np
import pytest

from probsum.operators import ordering, pairs, rectangles, samples
from probsum.plans.costs import build_cost
from probsum.sources.workloads import block_matrix


def test_policies():
    scores = [("b", "c", 9), ("a", "b", 8), ("c", "d", 6), ("a", "d", 1)]
    assert pairs.pick_pairs(scores, 2, "correlation") == [("b", "c"), ("a", "b")]
    assert sorted(pairs.pick_pairs(scores, 2, "cover")) == [("a", "b"), ("c", "d")]
    assert sorted(pairs.pick_pairs(scores, 2, "cover", most_subsets=0)) != []
    assert len(pairs.pick_pairs(scores, 9, "mi_tree")) == 3
    assert ("b", "c") not in pairs.pick_pairs(scores, 3, "correlation", exclude=("b",))
    assert pairs.Budget(3000, 2).per_pair == 1500 and pairs.Budget(3000, 3).per_pair == 1000


@pytest.mark.parametrize("rule", ["variance", "median"])
@pytest.mark.parametrize("order", ["breadth", "best_first"])
def test_leaves_cover_and_are_disjoint(rule, order):
    m = np.random.default_rng(0).integers(0, 50, (9, 11))
    x, y = ordering.order_axes(m, "weighted_index")
    leaves = rectangles.kd_rectangles(m, 17, rule, order, x, y)
    seen = np.zeros_like(m)
    for z in leaves:
        seen[np.ix_(z.x_codes, z.y_codes)] += 1
        assert m[np.ix_(z.x_codes, z.y_codes)].sum() == z.n
    assert (seen == 1).all() and len(leaves) == 17


def test_split_is_minimal():
    m = np.random.default_rng(1).integers(0, 9, (6, 7))
    pre = rectangles.Prefix(m)
    sse = lambda z: ((z - z.mean()) ** 2).sum()
    for axis in (0, 1):
        err, cut = rectangles.best_split(pre, (1, 6, 0, 7), axis)
        z = m[1:6] if axis == 0 else m[1:6].T
        brute = [sse(z[:c]) + sse(z[c:]) for c in range(1, len(z))]
        assert np.isclose(err, min(brute))
        assert cut == int(np.argmin(brute)) + (2 if axis == 0 else 1)


def test_seeded_cuts_and_axis_cuts():
    m = np.random.default_rng(2).integers(0, 9, (8, 6))
    for z in rectangles.kd_rectangles(m, 12, seed_x=[3, 5]):
        assert set(z.x_codes) in ({0, 1, 2}, {3, 4}, {5, 6, 7})
    assert rectangles.axis_cuts([1, 1, 1, 9, 9, 5], 3) == [3, 5]
    assert rectangles.merge_rects({"a": {1}, "b": {2}}, {"a": {3}}) == {"a": {1, 3}, "b": {2}}


def test_orderings_are_permutations_at_a_fixed_point():
    m = ordering.shuffled(block_matrix(), 3)
    for kind in ordering.KINDS:
        x, y = ordering.order_axes(m, kind)
        assert sorted(x) == sorted(y) == list(range(12))
        again = ordering.order_axes(m[np.ix_(x, y)], kind)
        assert (again[0] == np.arange(12)).all() and (again[1] == np.arange(12)).all()


def test_ordering_restores_blocks():
    t = {k: rectangles.kd_error_trials(block_matrix(), [12, 30], k).set_index("leaves") for k in ("natural", "zero_index", "weighted_index")}
    assert t["weighted_index"].loc[30, "mean"] <= t["natural"].loc[30, "mean"]
    assert t["weighted_index"].loc[30, "mean"] < 1e-6 and t["weighted_index"].loc[30, "std"] < 1e-6
    assert rectangles.kd_error(block_matrix(), rectangles.kd_rectangles(block_matrix(), 30)) < 1e-6


def test_stratum_cap():
    assert samples.stratum_cap([100, 3, 50], 40) == 18
    assert samples.stratum_cap([5, 5], 100) == 5


def test_cost_signs():
    assert [np.sign(build_cost(5000, b, 1000, 0.1)["difference"]) for b in (2, 3, 4)] == [-1, 1, 1]


def test_heavier_budget_never_raises_error_of_nested_trees():
    m = np.random.default_rng(5).integers(0, 90, (10, 10))
    pooled = [rectangles.kd_error(m, rectangles.kd_rectangles(m, b)) for b in (4, 16, 64)]
    total = [sum(z.sse for z in rectangles.kd_rectangles(m, b)) for b in (4, 16, 64)]
    assert total == sorted(total, reverse=True) and pooled[-1] <= pooled[0]


def test_pair_intersections_brute():
    rng = np.random.default_rng(0)
    sets = [set(rng.choice(12, 5, replace=False)) for _ in range(6)]
    assert any(a & b for a, b in combinations(sets, 2))
