"""The polynomial against brute force and the worked examples."""

import numpy as np
import pytest

from probsum.operators import joins
from probsum.plans import infer
from probsum.plans.forest import ForestModel, build_model
from probsum.plans.model import EvalOptions, Family, Model, TooManyTerms
from probsum.plans.summary import family_of_sets


def random_model(seed, pairs=(("a", "b"), ("b", "c"), ("c", "d")), n=400):
    rng = np.random.default_rng(seed)
    sizes = {"a": 6, "b": 5, "c": 4, "d": 3}
    data = {a: rng.integers(0, s, n) for a, s in sizes.items()}
    values = {a: np.bincount(data[a], minlength=s).astype(float) for a, s in sizes.items()}
    families = []
    for a, b in pairs:
        gx, gy = rng.integers(0, 3, sizes[a]), rng.integers(0, 2, sizes[b])
        cells = [(i, j) for i in range(3) for j in range(2) if (gx == i).any() and (gy == j).any()][: rng.integers(1, 5)]
        ma, mb = np.array([gx == i for i, _ in cells]), np.array([gy == j for _, j in cells])
        t = [(ma[k][data[a]] & mb[k][data[b]]).sum() for k in range(len(cells))]
        families.append(Family((a, b), {a: ma, b: mb}, np.array(t, float)))
    return Model(values, families, n)


def randomised(m, seed):
    rng = np.random.default_rng(seed)
    m.delta = [np.where(d > 0, rng.random(len(d)) * 3, 0) for d in m.delta]
    return m


@pytest.mark.parametrize("seed", range(6))
def test_factorised_equals_expanded(seed):
    m = randomised(random_model(seed), seed)
    _, w = infer.expand(m)
    assert np.isclose(w.sum(), m.evaluate())
    assert np.isclose(m.eliminate(), m.evaluate())
    flat = Model(m.values, m.families, m.n, split_components=False)
    flat.delta = m.delta
    assert np.isclose(flat.evaluate(), m.evaluate())


def test_components_multiply():
    m = randomised(random_model(3, (("a", "b"), ("c", "d"))), 1)
    assert len(m.components) == 2
    flat = Model(m.values, m.families, m.n, split_components=False)
    flat.delta = m.delta
    assert np.isclose(flat.evaluate(), m.evaluate())
    assert m.size()["terms"] < flat.size()["terms"]


@pytest.mark.parametrize("seed", range(3))
def test_query_forms_agree(seed):
    m = random_model(seed).solve(max_sweeps=200, tol=1e-7)
    w = {"a": infer.mask(m, "a", [1, 3]), "c": infer.mask(m, "c", [0])}
    e = infer.estimate(m, w)
    for method in ("points", "extend", "eliminate"):
        assert np.isclose(infer.estimate(m, w, method), e)
    point = {"a": infer.mask(m, "a", [2]), "d": infer.mask(m, "d", [1])}
    assert np.isclose(infer.estimate(m, point, "derivative"), infer.estimate(m, point))
    for o in (EvalOptions(), EvalOptions(cache=False), EvalOptions(masks=False), EvalOptions(zeros=False)):
        assert np.isclose(m.evaluate_cached(w, o)[0], m.evaluate(w))


def test_groups_equal_points_and_parts_sum():
    m = random_model(5).solve(max_sweeps=100, tol=1e-7)
    for by in (["a"], ["a", "c"], ["d", "b"], ["c", "a", "d"]):
        g = infer.estimate_groups(m, by)
        p, ended = infer.estimate_points(m, by)
        assert not ended and np.allclose(g, p)
        assert np.isclose(g.sum(), m.n)
    assert infer.estimate_points(m, ["a", "c"], budget_s=0.0)[1]


@pytest.mark.parametrize("seed", range(4))
def test_forest_equals_terms(seed):
    m = randomised(random_model(seed), seed)
    f = ForestModel(m.values, m.families, m.n)
    f.delta = m.delta
    w = {"a": infer.mask(m, "a", [0, 2])}
    assert np.isclose(f.evaluate(w), m.evaluate(w))
    for a in m.attrs:
        assert np.allclose(f.partial_values(a, w), m.partial_values(a, w))
    for i in range(len(m.families)):
        assert np.allclose(f.partial_rects(i)[0], m.partial_rects(i)[0])
    assert np.allclose(infer.estimate_groups(f, ["a", "d"], w), infer.estimate_groups(m, ["a", "d"], w))


def test_solvers_reach_the_same_model():
    out = []
    for method, sweeps in (("block", 300), ("coordinate", 300), ("gradient", 6000)):
        m = random_model(1, (("a", "b"), ("b", "c"))).solve(method=method, max_sweeps=sweeps, tol=1e-6)
        assert max(m.residuals().values()) < 1e-2
        out.append(infer.estimate_groups(m, ["a", "b", "c"]))
    assert np.allclose(out[0], out[1], atol=1e-2) and np.allclose(out[0], out[2], atol=0.1)


def test_dual_does_not_fall():
    m = random_model(2)
    last = m.dual()
    for _ in range(10):
        for a in m.attrs:
            m.step_values(a)
        for f in range(len(m.families)):
            m.step_rects(f)
        assert m.dual() >= last - 1e-6
        last = m.dual()
    assert np.isclose(infer.entropy(m), -last)


def test_statistics_are_recovered_and_zeros_pinned():
    m = random_model(4).solve(max_sweeps=300, tol=1e-7)
    for a in m.attrs:
        for j, s in enumerate(m.values[a]):
            assert abs(infer.expected_statistic(m, a, j) - s) < 1e-3
    zero = Model({"a": np.array([5.0, 0.0, 5.0]), "b": np.array([10.0])}).solve()
    assert infer.estimate(zero, {"a": infer.mask(zero, "a", [1])}) == 0
    one = Model({"a": np.array([10.0, 0.0]), "b": np.array([4.0, 6.0])}).solve(method="coordinate")
    assert np.isclose(infer.estimate(one, {"b": infer.mask(one, "b", [1])}), 6)


def test_five_row_instance():
    """A in {a1, a2}, B in {b1, b2}; frequency vector (2, 1, 0, 2)."""
    m = Model({"a": np.array([3.0, 2.0]), "b": np.array([2.0, 3.0])}).solve()
    assert np.isclose(infer.estimate(m, {"a": infer.mask(m, "a", [0])}), 3)
    assert np.isclose(infer.worlds_partition(m), m.evaluate() ** 5)


def test_ten_row_instance():
    """Eight monomials; one-dimensional targets 3/7, 8/2, 6/4 and the two-dimensional ones 2, 1, 5, 1."""
    sizes = {"a": 2, "b": 2, "c": 2}
    ab = family_of_sets([{"a": {0}, "b": {0}}, {"a": {1}, "b": {1}}], [2, 1], sizes)
    bc = family_of_sets([{"b": {0}, "c": {0}}, {"b": {1}, "c": {0}}], [5, 1], sizes)
    m = Model({"a": np.array([3.0, 7]), "b": np.array([8.0, 2]), "c": np.array([6.0, 4])}, [ab, bc], 10).solve(max_sweeps=500, tol=1e-9)
    tuples, w = infer.expand(m)
    assert len(tuples) == 8 and np.isclose(w.sum(), m.evaluate())
    assert max(m.residuals().values()) < 1e-6
    assert len(m.components) == 1 and m.components[0].terms <= 9


def cube():
    span = lambda lo, hi: set(range(lo - 1, hi))
    d1 = {"a": span(101, 200), "b": span(501, 600)}
    d4 = {"a": span(101, 150), "b": span(551, 600), "c": span(801, 850)}
    d2 = {"b": span(551, 650), "c": span(801, 900)}
    d3 = {"b": span(651, 700), "c": span(701, 800)}
    return d1, d2, d3, d4


def test_thousand_cube():
    """Four rectangles on domains of a thousand values: the factorised form has 6,400 variable occurrences."""
    d1, d2, d3, d4 = cube()
    sizes = {x: 1000 for x in "abc"}
    values = {x: np.ones(1000) for x in "abc"}
    # family order: AB, BC, and the three-dimensional rectangle apart
    fams = [family_of_sets([d1], [1.0], sizes), family_of_sets([d2, d3], [1.0, 1.0], sizes)]
    m = Model(values, fams, 1000)
    c = m.components[0]
    assert c.terms == 1 + 1 + 2 + 1
    full = {tuple(np.flatnonzero(r >= 0)) for r in c.rects}
    assert full == {(), (0,), (1,), (0, 1)}
    with3d = Model(values, [*fams, family_of_sets([d4], [1.0], sizes)], 1000)
    sets = sorted(tuple(r >= 0) for r in with3d.components[0].rects)
    assert (True, True, True) in sets  # all three meet
    w = {"a": infer.mask(m, "a", range(35, 150)), "c": infer.mask(m, "c", range(659, 834))}
    assert np.isclose(m.evaluate_cached(w)[0], m.evaluate(w))


def test_joint_intersection_is_needed():
    """Three sets of values that meet in pairs but not together form no group."""
    sizes = {"a": 3, "b": 2, "c": 2, "d": 2}
    rects = [family_of_sets([{"a": s, o: {0}}], [1], sizes) for s, o in (({0, 1}, "b"), ({1, 2}, "c"), ({0, 2}, "d"))]
    m = Model({k: np.ones(s) * (6 / s) for k, s in sizes.items()}, rects, 6)
    assert m.components[0].terms == 1 + 3 + 3
    randomised(m, 1)
    assert np.isclose(infer.expand(m)[1].sum(), m.evaluate())


def test_term_limit_and_fallback():
    m = random_model(0)
    with pytest.raises(TooManyTerms):
        Model(m.values, m.families, m.n, max_terms=2)
    assert isinstance(build_model(m.values, m.families, m.n, max_terms=2), ForestModel)


def test_invalid_statistics_are_refused():
    sizes = {"a": 2, "b": 2}
    v = {"a": np.array([5.0, 5]), "b": np.array([4.0, 6])}
    with pytest.raises(ValueError):
        Model(v, [family_of_sets([{"a": {0, 1}, "b": {0}}, {"a": {0}, "b": {0, 1}}], [1, 1], sizes)])
    with pytest.raises(ValueError):
        Model({"a": np.array([5.0, 5]), "b": np.array([4.0, 7])}, n=10)


def test_probability_sum_variance():
    m = Model({"a": np.array([6.0, 4]), "b": np.array([7.0, 3])}).solve()
    p = 0.6 * 0.7
    assert np.isclose(infer.tuple_probability(m, {"a": 0, "b": 0}), 1 - (1 - p) ** 10)
    assert np.isclose(infer.variance(m, {"a": infer.mask(m, "a", [0])}), 10 * 0.6 * 0.4)
    one = Model({"a": np.array([0.6, 0.4]), "b": np.array([1.0])}, n=1).solve()
    assert np.isclose(infer.tuple_probability(one, {"a": 0}), 0.6)
    assert np.isclose(infer.estimate_sum(m, "a", np.array([10.0, 20.0])), 6 * 10 + 4 * 20)
    assert np.isclose(infer.estimate_avg(m, "a", np.array([10.0, 20.0])), 14)
    any_ = infer.estimate_any(m, [{"a": infer.mask(m, "a", [0])}, {"b": infer.mask(m, "b", [0])}])
    assert np.isclose(any_, 10 * (0.6 + 0.7 - 0.42))
    lp = infer.log_probability(m, {(0, 0): 2, (1, 1): 1})
    assert np.isclose(lp, 2 * np.log(0.42) + np.log(0.12))
    assert infer.rounded(0.49) == 0 and infer.rounded(0.5) == 1 and not infer.exists(0.49)


def test_warm_start_needs_fewer_sweeps():
    m = random_model(7).solve(max_sweeps=400, tol=1e-4)
    cold = random_model(7)
    for x in (m, cold):
        x.values["a"] = x.values["a"] + np.array([1, -1, 0, 0, 0, 0])
    n0 = len(m.history)
    m.solve(max_sweeps=400, tol=1e-3)
    cold.solve(max_sweeps=400, tol=1e-3)
    assert len(m.history) - n0 <= len(cold.history)


# -- joins of summaries ---------------------------------------------------------


def test_join_by_keys_is_exact():
    a, b, c = np.array([3.0, 2, 5]), np.array([1.0, 4, 2]), np.array([2.0, 2, 3])
    x, y = Model({"k": a}).solve(), Model({"k": b}).solve()
    assert np.isclose(joins.estimate_join([x, y], [["k"]]), a @ b)
    assert np.isclose(joins.estimate_join([x, y, Model({"k": c}).solve()], [["k"], ["k"]]), (a * b * c).sum())
    assert np.isclose(joins.estimate_join([x, y, Model({"k": c}).solve()], [["k"], ["k"]], used=range(1, 3)), b @ c)


def test_composite_keys():
    m = np.array([[2.0, 1], [0, 3]])
    fam = [Family(("k", "l"), {"k": np.eye(2, dtype=bool)[[0, 0, 1, 1]], "l": np.eye(2, dtype=bool)[[0, 1, 0, 1]]}, m.ravel())]
    x = Model({"k": m.sum(1), "l": m.sum(0)}, fam).solve(max_sweeps=300, tol=1e-9)
    assert np.isclose(joins.estimate_join([x, x], [["k", "l"]]), (m * m).sum(), rtol=1e-6)


def test_shared_boundaries_shorten_the_sum():
    """Domains of three, cuts [b1, b2], [b3]: one representative per group gives the full sum, unless boundaries differ."""
    cuts = [2]
    r = np.array([[2.0, 4, 1], [2, 4, 1], [5, 0, 1]])  # rows: join value
    left = joins.share_boundaries({"b": r.sum(1), "a": r.sum(0)}, r, "b", "a", cuts, 4).solve(max_sweeps=200)
    s = np.array([[1.0, 3], [1, 3], [6, 2]])
    right = joins.share_boundaries({"b": s.sum(1), "c": s.sum(0)}, s, "b", "c", cuts, 4).solve(max_sweeps=200)
    full = joins.estimate_join([left, right], [["b"]])
    assert np.isclose(joins.estimate_join_grouped(left, right, "b", cuts), full)
    uneven = Model({"b": np.array([1.0, 7, 2])}).solve()
    with pytest.raises(ValueError):
        joins.estimate_join_grouped(left, uneven, "b", cuts)
