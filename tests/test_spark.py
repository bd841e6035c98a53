"""Spark side: groups as joins, terms as tables, persistence, domains, updates, accuracy orderings."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from probsum.functions.domain import Attr, bucket_weights, codes_matching, encode
from probsum.operators import samples
from probsum.plans import groups, infer
from probsum.plans.model import Family, Model
from probsum.plans.summary import Summary, family_of_sets, summarise
from probsum.plans.terms import evaluate_distributed, term_frame
from probsum.queries.experiments import pair_budget
from probsum.sources import workloads as wl
from probsum.streaming.updates import Maintained, RebuildPolicy, as_delta


def _families(seed=0):
    rng = np.random.default_rng(seed)
    sizes = {"a": 70, "b": 9, "c": 5}
    out = []
    for x, y in (("a", "b"), ("b", "c"), ("a", "c")):
        part = rng.integers(0, 4, sizes[x])
        out.append(
            Family((x, y), {x: np.array([part == i for i in range(4)]), y: rng.random((4, sizes[y])) < 0.5}, np.ones(4))
        )
    return out, sizes


def _brute(fams):
    from itertools import product

    out, ids = set(), []
    base = 0
    for f in fams:
        ids.append([None, *range(base, base + f.size)])
        base += f.size
    for pick in product(*ids):
        chosen = [(f, i - sum(g.size for g in fams[:k])) for k, (f, i) in enumerate(zip(fams, pick)) if i is not None]
        if len(chosen) < 2:
            continue
        ok = True
        for a in {a for f, _ in chosen for a in f.attrs}:
            m = np.logical_and.reduce([f.masks[a][r] for f, r in chosen if a in f.attrs])
            ok &= bool(m.any())
        if ok:
            out.add(tuple(sorted(i for i in pick if i is not None)))
    return out


@pytest.mark.parametrize("mode", ["levelwise", "per_subset", "outer_once"])
def test_compatible_groups(spark, mode):
    fams, _ = _families()
    rects = groups.rect_frame(spark, fams)
    rows = groups.compatible_groups(rects, [0, 1, 2], mode).collect()
    got = [tuple(sorted(r["members"])) for r in rows]
    assert len(got) == len(set(got)) and set(got) == _brute(fams)


def test_worked_groups(spark):
    """Five rectangles: groups {1,2}, {1,4}, {1,5}, {2,4}, {1,2,4}; the third meets none."""
    span = lambda lo, hi: set(range(lo - 1, hi))
    sizes = {x: 1000 for x in "abc"}
    ab = family_of_sets([{"a": span(101, 200), "b": span(501, 600)}], [1], sizes)
    bc = family_of_sets(
        [{"b": span(551, 650), "c": span(801, 900)}, {"b": span(651, 700), "c": span(701, 800)}, {"b": span(501, 550), "c": span(701, 800)}], [1, 1, 1], sizes
    )
    abc = family_of_sets([{"a": span(101, 150), "b": span(551, 600), "c": span(801, 850)}], [1], sizes)
    name = {0: 1, 1: 2, 2: 3, 3: 5, 4: 4}
    rects = groups.rect_frame(spark, [ab, bc, abc])
    got = {tuple(sorted(name[i] for i in r["members"])) for r in groups.compatible_groups(rects, [0, 1, 2]).collect()}
    assert got == {(1, 2), (1, 4), (1, 5), (2, 4), (1, 2, 4)}
    assert {name[r["stat_id"]] for r in groups.prune_isolated(rects).collect()} == {1, 2, 4, 5}


def test_distributed_evaluation(spark):
    fams, sizes = _families(2)
    fams = [Family(f.attrs, f.masks, np.zeros(f.size)) for f in fams[:2]]
    # make rectangles disjoint through their first attribute
    m = Model({a: np.ones(s) * (630 / s) for a, s in sizes.items()}, fams, 630)
    m.delta = [np.random.default_rng(1).random(f.size) * 2 for f in fams]
    w = {"b": infer.mask(m, "b", [1, 2, 3])}
    assert np.isclose(evaluate_distributed(term_frame(spark, m), m, w), m.evaluate(w))


def test_domains(spark):
    df = spark.createDataFrame([("x", 1.0), ("y", 12.0), (None, 3.0), ("x", 25.0)], "s string, v double")
    codes, domain = encode(df, [Attr("s"), Attr("v", 10, 0, 3)])
    assert sorted(tuple(r) for r in codes.collect()) == [(0, 0), (0, 2), (1, 1)]
    assert codes_matching(domain, "s", "s like 'x%'") == [0]
    assert codes_matching(domain, "v", "v >= 1") == [1, 2]
    assert bucket_weights(domain, "v", 5, 20) == {0: 0.5, 1: 1.0}
    other = spark.createDataFrame([("z", 1.0)], "s string, v double")
    assert encode(other, [Attr("s"), Attr("v", 10, 0, 3)], domain, unknown="mark")[0].first()["s"] == -1
    assert encode(other, [Attr("s"), Attr("v", 10, 0, 3)], domain)[0].count() == 0


def test_save_and_load(spark, sf, tmp_path):
    s = summarise(wl.shop_coarse(spark, sf), wl.coarse_attrs(), [("p_brand", "p_type"), ("net", "gross")], per_pair=30, max_sweeps=10)
    s.save(str(tmp_path / "s"))
    t = Summary.load(spark, str(tmp_path / "s"))
    where = {"p_type": "p_type like 'S%'", "net": "net between 3 and 20"}
    assert np.isclose(s.count(where), t.count(where))
    assert t.storage()["parameters"] > 0
    est, var = s.count(where, with_variance=True)
    assert 0 <= est <= s.model.n and var >= 0


def test_histogram_summary(spark):
    s = Summary.from_histograms(spark, {"a": np.array([6, 4]), "b": np.array([7, 3])}).solve()
    assert np.isclose(s.count({"a": "a = 0", "b": "b = 1"}), 1.8)


def test_samples(spark, sf):
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    rel = wl.shop_coarse(spark, sf, keys=True)
    n = rel.count()
    for exact in (True, False):
        s = samples.stratified_sample(rel, ["p_brand", "p_type"], 0.1, keys, exact)
        assert abs(s.agg(F.sum("weight")).first()[0] - n) < (1e-6 if exact else 0.5) * n
    u = samples.uniform_sample(rel, 0.1, keys)
    assert abs(samples.sample_count(u) - n) < 0.3 * n


def test_updates_equal_final_statistics(spark):
    rows = [(i % 3, (i * 7) % 4) for i in range(60)]
    df = spark.createDataFrame(rows, "a int, b int")
    attrs = [Attr("a", 1, 0, 3), Attr("b", 1, 0, 4)]
    s = summarise(df, attrs, [("a", "b")], per_pair=4, max_sweeps=50)
    kept = Maintained(s, {("a", "b"): np.ones((3, 4))})
    new = spark.createDataFrame([(0, 0)] * 30 + [(1, 1)] * 5, "a int, b int")
    gone = df.limit(10)
    kept.apply_delta(as_delta(gone, new))
    assert kept.pending.n == 25 and kept.pending.rows == 41  # inserts and deletes of the same tuple cancel
    policy = RebuildPolicy(max_updates=40)
    assert "updates" in policy.reasons(kept) and "idle" in policy.reasons(kept, idle=True)
    after = kept.refresh(max_sweeps=300, tol=1e-6)
    final = df.exceptAll(gone).unionAll(new)
    for a in ("a", "b"):
        truth = {r[a]: r["count"] for r in final.groupBy(a).count().collect()}
        est = infer.estimate_groups(after.model, [a])
        assert all(abs(est[k] - v) < 0.5 for k, v in truth.items())
    kept.apply_delta(as_delta(None, spark.createDataFrame([(0, 0)] * 500, "a int, b int")))
    assert RebuildPolicy(chi2_high=1.0).reasons(Maintained(Summary(spark, s.domain, Model(s.model.values), s.attrs), {("a", "b"): np.diag([50, 50, 50, 50])[:3]}))


def test_budget_orderings(spark, sf):
    """More rectangles on the queried pair lower the heavy error; empty cells are best on absent values."""
    rows = pair_budget(spark, sf, (50, 400))
    e = {(h, b, k): v for h, b, k, v in rows}
    assert e["heavy", 400, "heavy"] < e["heavy", 50, "heavy"]
    assert e["kd", 400, "heavy"] < e["kd", 50, "heavy"]
    assert e["heavy", 400, "heavy"] <= e["empty", 400, "heavy"]


def test_queries_have_oracles_and_run(spark, sf):
    from probsum import queries

    queries.load()
    assert len(queries.QUERIES) > 120 and set(queries.ORACLES) <= set(queries.QUERIES)
    for name in ("stat_values", "rect_heavy", "join_interval", "set_except_all", "scan_summary"):
        assert queries.QUERIES[name](spark, sf).count() >= 0
