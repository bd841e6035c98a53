"""The experiments on the given tables: accuracy of summaries and samples, budgets, orderings, times."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.functions.domain import Attr, drop_nulls, encode, equi_width
from probsum.operators import rectangles, samples, stats
from probsum.operators.ordering import order_axes
from probsum.plans import infer
from probsum.plans.model import EvalOptions, Model
from probsum.plans.summary import Counts, Summary, choose_family, collect_counts, summarise
from probsum.plans.terms import evaluate_distributed, factor_frame, term_frame
from probsum.queries import query
from probsum.sources import workloads as wl
from probsum.sources.tables import stored

ROWS = "method string, template string, kind string, truth double, est double"


def fit_summaries(rel, attrs: list[Attr], total: int, which=wl.SUMMARIES, sweeps: int = 30, ordering: str = "natural", pairs=wl.PAIRS) -> dict[str, Summary]:
    """One summary per pair choice, the total budget of two-dimensional statistics shared by its pairs; `rel` is counted once, or its Counts."""
    used = sorted({i for ids in which.values() for i in ids})
    counts = rel if isinstance(rel, Counts) else collect_counts(rel, attrs, [pairs[i] for i in used])
    out = {}
    for name, ids in which.items():
        chosen = [pairs[i] for i in ids]
        out[name] = summarise(counts, pairs=chosen, per_pair=total // max(len(chosen), 1), ordering=ordering, max_sweeps=sweeps)
    if counts is not rel:
        counts.release()
    return out


def hitter_rows(codes: DataFrame, sizes: dict[str, int], template, heavy=100, light=100, absent=200) -> list[tuple]:
    """(kind, codes.., n) of a template, at most 400 rows."""
    rows = wl.hitters(codes, list(template), sizes, heavy, light, absent).collect()
    return [(r["kind"], tuple(r[a] for a in template), r["n"]) for r in rows]


def score(codes: DataFrame, sizes: dict[str, int], summaries: dict[str, Summary], sampled: dict[str, DataFrame], templates) -> list[tuple]:
    """(method, template, kind, truth, est) of hitters under every summary and sample (frames of codes with a weight).

    The groups of all templates are counted in one pass over the codes, and one over each sample.
    """
    truth = stats.dense_groups(codes, sizes, list(templates))
    found = {t: wl.hitters_of(truth[t], t) for t in templates}
    out = []
    for t in templates:
        for method, s in summaries.items():
            est = infer.estimate_groups(s.model, list(t))
            out += [(method, ",".join(t), kind, float(n), float(est[point])) for kind, point, n in found[t]]
    for method, got in side_by_side(lambda sample: stats.dense_groups(sample, sizes, list(templates), "weight"), sampled).items():
        for t in templates:
            out += [(method, ",".join(t), kind, float(n), float(got[t][point])) for kind, point, n in found[t]]
    return out


def coded_samples(rel: DataFrame, codes_of, rate: float, strata: dict[str, list[str]]) -> dict[str, DataFrame]:
    """The uniform sample and one stratified sample per pair, under the summaries' codes; `rel` holds the keys of lineitem."""
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    out = {"uniform": codes_of(samples.uniform_sample(rel, rate, keys))}
    made = side_by_side(lambda cols: codes_of(samples.stratified_sample(rel, cols, rate, keys)), strata)
    return out | {f"stratified {name}": sample for name, sample in made.items()}


def side_by_side(run, given: dict, most: int = 4) -> dict:
    """{name: run(value)}, some at a time: the Spark jobs of one fill the cores that another leaves."""
    with ThreadPoolExecutor(most) as pool:
        return dict(zip(given, pool.map(run, given.values()), strict=True))


def _with_codes(domain: DataFrame, attrs: list[Attr]):
    def run(df: DataFrame) -> DataFrame:
        out = drop_nulls(df, [a.name for a in attrs])
        for a in attrs:
            if a.arithmetic:
                out = out.withColumn(a.name, equi_width(a.name, a.width, a.lo, a.size))
                continue
            book = domain.where(F.col("attr") == a.name).select(F.col("label").alias("_l"), F.col("code").alias("_c"))
            out = out.join(F.broadcast(book), F.col(a.name).cast("string") == F.col("_l")).withColumn(a.name, F.col("_c")).drop("_l", "_c")
        return out

    return run


def coarse_accuracy(spark, d, templates, total: int = 300, rate: float = 0.01, which=wl.SUMMARIES, with_samples: bool = True) -> pd.DataFrame:
    attrs = wl.coarse_attrs()
    rel = stored(wl.shop_coarse(spark, d, keys=with_samples), "shop-coarse")
    counts = collect_counts(rel, attrs, [wl.PAIRS[i] for i in sorted({i for ids in which.values() for i in ids})])
    summaries = fit_summaries(counts, attrs, total, which)
    strata = {str(i): list(p) for i, p in wl.PAIRS.items()} if with_samples else {}
    codes_of = _with_codes(counts.domain, attrs)
    sampled = coded_samples(rel, codes_of, rate, strata) if with_samples else {}
    rows = score(codes_of(rel), counts.sizes, summaries, sampled, templates)
    counts.release()
    counts.domain.unpersist()
    return pd.DataFrame(rows, columns=[c.split()[0] for c in ROWS.split(", ")])


def accuracy_table(rows: pd.DataFrame) -> pd.DataFrame:
    """(method, template, heavy, light, f) per method and template."""
    e = np.where(rows.truth + rows.est == 0, 0.0, (rows.truth - rows.est).abs() / (rows.truth + rows.est).clip(lower=1e-300))
    rows = rows.assign(error=e, said=np.floor(rows.est + 0.5) > 0)
    out = []
    for (m, t), g in rows.groupby(["method", "template"]):
        light, absent = g[g.kind == "light"], g[g.kind == "absent"]
        hit, said = light.said.sum(), light.said.sum() + absent.said.sum()
        p, r = hit / said if said else 0.0, hit / len(light) if len(light) else 0.0
        out.append((m, t, g[g.kind == "heavy"].error.mean(), light.error.mean(), 2 * p * r / (p + r) if p + r else 0.0))
    return pd.DataFrame(out, columns=["method", "template", "heavy", "light", "f"])


_TABLE = "method string, template string, heavy double, light double, f double"
SIX = [("p_brand", "p_size"), ("p_brand", "p_size", "p_type"), ("p_size", "p_type"), ("net", "gross"), ("p_brand", "p_type"), ("ship_month", "p_size", "p_type")]


@query()
def accuracy_heavy_light(spark, d):
    """Six templates: mean error on heavy and light hitters and F of every summary, the uniform and four stratified samples."""
    return spark.createDataFrame(accuracy_table(coarse_accuracy(spark, d, SIX)), _TABLE)


@query()
def accuracy_difference(spark, d):
    """Errors of every method less those of the summary on pairs 1, 2 and 3."""
    t = accuracy_table(coarse_accuracy(spark, d, SIX))
    ref = t[t.method == "1&2&3"].set_index("template")
    t["heavy"] -= t.template.map(ref.heavy)
    t["light"] -= t.template.map(ref.light)
    return spark.createDataFrame(t, _TABLE)


@query()
def accuracy_fifteen(spark, d):
    """Mean F of every method over fifteen templates."""
    t = accuracy_table(coarse_accuracy(spark, d, wl.FIFTEEN))
    return spark.createDataFrame(t.groupby("method", as_index=False).f.mean(), "method string, f double")


@query()
def accuracy_fine(spark, d):
    """The fine relation: error and F of none, brand with type, and net with gross."""
    attrs, rel = wl.fine_attrs(), stored(wl.shop_fine(spark, d), "shop-fine")
    pairs = {3: ("net", "gross"), 4: ("brand_name", "size_type")}
    counts = collect_counts(rel, attrs, list(pairs.values()))
    summaries = fit_summaries(counts, attrs, 300, {"none": [], "3": [3], "4": [4], "3&4": [3, 4]}, pairs=pairs)
    rows = score(_with_codes(counts.domain, attrs)(rel), counts.sizes, summaries, {}, [("brand_name", "size_type"), ("net", "gross"), ("brand_name", "net")])
    counts.release()
    counts.domain.unpersist()
    return spark.createDataFrame(accuracy_table(pd.DataFrame(rows, columns=["method", "template", "kind", "truth", "est"])), _TABLE)


@query()
def particles_scaling(spark, d):
    """One to three snapshots: error on four-attribute selections, seconds a query, for summary and samples."""
    attrs = wl.particle_attrs()
    pairs = [("density", "mass"), ("mass", "y"), ("density", "x"), ("density", "z"), ("density", "grp")]
    out = []
    for last in range(3):
        rel = wl.particles_like(spark, d).where(f"snap <= {last}")
        codes, domain = encode(rel, attrs)
        codes = codes.persist()
        codes.count()
        for name, ps in (("none", []), ("all", pairs)):
            s = summarise(rel, attrs, ps, per_pair=100, max_sweeps=30)
            found = hitter_rows(codes, s.model.sizes, ("density", "mass", "grp", "type"), 50, 50, 50)
            began = time.perf_counter()
            est = [
                infer.estimate(s.model, {a: infer.mask(s.model, a, [x]) for a, x in zip(("density", "mass", "grp", "type"), p)})
                for _, p, _ in found
            ]
            each = (time.perf_counter() - began) / max(len(found), 1)
            err = np.mean([abs(n - e) / (n + e) if n + e else 0.0 for (_, _, n), e in zip(found, est)])
            out.append((last + 1, name, float(err), each))
        uniform = codes.sample(0.01, 42).withColumn("weight", F.lit(100.0))
        counts = codes.groupBy("density", "grp").agg(F.count(F.lit(1)).alias("n_h"))
        cap = samples.cap_of(counts.withColumnRenamed("n_h", "n"), max(int(codes.count() * 0.01), 1))
        strat = codes.join(counts, ["density", "grp"]).where(F.rand(7) < F.lit(cap) / F.col("n_h")).withColumn("weight", F.greatest(F.lit(1.0), F.col("n_h") / F.lit(float(cap))))
        for name, sample in (("uniform", uniform), ("stratified", strat)):
            sample = sample.persist()
            got = {tuple(r)[:4]: r["est"] for r in samples.sample_groups(sample, ["density", "mass", "grp", "type"]).collect()}
            began = time.perf_counter()
            k, p, _ = found[0]
            samples.sample_count(sample, f"density = {p[0]} and mass = {p[1]} and grp = {p[2]} and type = {p[3]}")
            each = time.perf_counter() - began
            err = np.mean([abs(n - got.get(p, 0.0)) / (n + got.get(p, 0.0)) if n + got.get(p, 0.0) else 0.0 for _, p, n in found])
            out.append((last + 1, name, float(err), each))
            sample.unpersist()
        codes.unpersist()
    return spark.createDataFrame(out, "snapshots int, method string, error double, seconds double")


def pair_budget(spark, d, budgets=(50, 100, 200, 400), sweeps: int = 30) -> list[tuple]:
    """(heuristic, budget, kind, error) on (ship_month, net, gross) with the pair (net, gross)."""
    attrs = [Attr("ship_month", 1, 0, 83), Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)]
    codes, _ = encode(wl.shop_pair(spark, d), attrs)
    cuboid = stats.base_cuboid(codes).persist()
    sizes = {a.name: a.size for a in attrs}
    values = {a: np.zeros(s) for a, s in sizes.items()}
    for r in stats.value_stats(cuboid).collect():
        values[r["attr"]][r["code"]] = r["n"]
    m = stats.matrix_of(stats.contingencies(cuboid, [("net", "gross")]), "net", "gross", (62, 81))
    xs, ys = np.nonzero(m)
    cells = sorted(zip(m[xs, ys].tolist(), xs.tolist(), ys.tolist()), key=lambda c: (-c[0], c[1], c[2]))
    zero = np.argwhere(m == 0)
    zero = zero[np.argsort((zero[:, 0] * 7919 + zero[:, 1] * 104729) % 1000003, kind="stable")][:200]
    kinds = {"heavy": cells[:100], "light": cells[-100:], "absent": [(0, int(x), int(y)) for x, y in zero]}
    out = []
    variants = {"kd median": {"rule": "median"}, "kd best_first": {"order": "best_first"}}
    for rule in ("heavy", "empty", "kd", *variants):
        for b in budgets:
            options = variants.get(rule, {})
            fam = choose_family(m, "net", "gross", b, rule.split()[0], "natural", sizes, **options)
            model = Model(values, [fam]).solve(max_sweeps=sweeps)
            est = infer.estimate_groups(model, ["net", "gross"])
            for kind, rows in kinds.items():
                e = [abs(n - est[x, y]) / (n + est[x, y]) if n + est[x, y] > 0 else 0.0 for n, x, y in rows]
                out.append((rule, b, kind, float(np.mean(e))))
    cuboid.unpersist()
    return out


@query()
def budget_curve(spark, d):
    """Heuristic x budget x kind of hitter."""
    return spark.createDataFrame(pair_budget(spark, d), "heuristic string, budget int, kind string, error double")


@query()
def ordering_effect(spark, d):
    """(ordering, template, heavy, light, f): natural order against the weighted index, on pairs 3 and 4."""
    attrs, rel = wl.coarse_attrs(), wl.shop_coarse(spark, d)
    codes, _ = encode(rel, attrs)
    codes = codes.persist()
    rows = []
    for name in ("natural", "weighted_index", "zero_index"):
        s = fit_summaries(rel, attrs, 300, {name: [3, 4]}, ordering=name)
        templates = [("p_brand", "p_size"), ("net", "gross"), ("p_brand", "net"), ("p_brand", "gross"), ("p_size", "net"), ("p_size", "gross")]
        rows += score(codes, s[name].model.sizes, s, {}, templates)
    codes.unpersist()
    return spark.createDataFrame(accuracy_table(pd.DataFrame(rows, columns=["method", "template", "kind", "truth", "est"])), _TABLE)


@query()
def ordering_trials(spark, d):
    """(ordering, leaves, mean, std): K-D error of ten shuffles of (net, gross) folded to 12 x 12."""
    attrs = [Attr("net", 62 / 12, 0, 12), Attr("gross", 81 / 12, 0, 12)]
    counts = collect_counts(wl.shop_coarse(spark, d), attrs)
    matrix = stats.matrix_of(counts.table, "net", "gross", (12, 12))
    parts = []
    for kind in ("natural", "zero_index", "weighted_index"):
        t = rectangles.kd_error_trials(matrix, range(6, 31, 3), kind)
        parts.append(t.assign(ordering=kind))
    return spark.createDataFrame(pd.concat(parts), "leaves int, mean double, std double, ordering string")


@query()
def ordering_heatmap(spark, d):
    """Leaves of (net, gross) before and after ordering: what a heat map with cuts would show."""
    rel = wl.shop_coarse(spark, d)
    codes, _ = encode(rel, [Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)])
    m = stats.matrix_of(stats.contingencies(stats.base_cuboid(codes)), "net", "gross", (62, 81))
    rows = []
    for kind in ("natural", "weighted_index"):
        x, y = order_axes(m, kind)
        leaves = rectangles.kd_rectangles(m, 60, x_order=x, y_order=y)
        rows += [(kind, i, list(z.x_codes), list(z.y_codes), z.n, z.sse) for i, z in enumerate(leaves)]
    return spark.createDataFrame(rows, "ordering string, leaf_id int, x_codes array<int>, y_codes array<int>, n long, sse double")


@query()
def phase_times(spark, d):
    """(pairs, per_pair, load_s, build_s, solve_s, terms, residual) over the grid of budgets on the fine relation."""
    rows = []
    all_pairs = [("net", "gross"), ("brand_name", "size_type"), ("size_type", "net")]
    counts = collect_counts(wl.shop_fine(spark, d), wl.fine_attrs(), all_pairs)
    for n, grid in ((2, (30, 75, 150, 1500)), (3, (20, 50, 100, 1000))):
        for per in grid:
            s = summarise(counts, pairs=all_pairs[:n], per_pair=per, max_sweeps=30)
            p = s.phases
            rows.append((n, per, p["load"], p["build"], p["solve"], int(s.model.size()["terms"]), max(s.model.residuals().values())))
    return spark.createDataFrame(rows, "pairs int, per_pair int, load_s double, build_s double, solve_s double, terms int, residual double")


@query()
def groupby_times(spark, d):
    """(by, groups, pointwise_s, batched_s, exact_s, ended): group-bys of two and three attributes, with and without the date."""
    rel = wl.shop_fine(spark, d)
    s = summarise(rel, wl.fine_attrs(), [("net", "gross"), ("brand_name", "size_type")], per_pair=75, max_sweeps=10)
    cached = rel.persist()
    cached.count()
    templates = [*wl.templates(wl.FINE, (2,), 8), *wl.templates(wl.FINE, (3,), 8)]
    rows = []
    for by in templates:
        t0 = time.perf_counter()
        _, ended = infer.estimate_points(s.model, list(by), budget_s=1.0)
        t1 = time.perf_counter()
        groups = int(np.prod([s.model.sizes[a] for a in by]))
        infer.estimate_groups(s.model, list(by))
        t2 = time.perf_counter()
        cached.groupBy(*by).agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n")).first()
        t3 = time.perf_counter()
        rows.append((",".join(by), groups, t1 - t0, t2 - t1, t3 - t2, ended))
    cached.unpersist()
    return spark.createDataFrame(rows, "by string, groups long, pointwise_s double, batched_s double, exact_s double, ended boolean")


@query()
def evaluation_switches(spark, d):
    """(options, seconds, hit_rate, estimate): evaluation with the cache, masks and zero tests on or off, and as a Spark job."""
    s = summarise(wl.shop_coarse(spark, d), wl.coarse_attrs(), [wl.PAIRS[1], wl.PAIRS[2], wl.PAIRS[3]], per_pair=60, max_sweeps=5)
    m = s.model
    w = {"p_size": infer.mask(m, "p_size", range(5)), "net": infer.mask(m, "net", [3])}
    p = m.evaluate()
    rows = []
    for name, o in (("all", EvalOptions()), ("no cache", EvalOptions(cache=False)), ("no masks", EvalOptions(masks=False)), ("no zero test", EvalOptions(zeros=False))):
        m.refresh()
        began = time.perf_counter()
        for _ in range(20):
            value, trace = m.evaluate_cached(w, o)
        rows.append((name, (time.perf_counter() - began) / 20, trace.hit_rate, m.n * value / p))
    terms = term_frame(spark, m)
    began = time.perf_counter()
    value = evaluate_distributed(terms, m, w)
    rows.append(("distributed", time.perf_counter() - began, 0.0, m.n * value / p))
    return spark.createDataFrame(rows, "options string, seconds double, hit_rate double, estimate double")


@query()
def model_size(spark, d):
    """(summary, terms, factors, variables, log10_monomials, parameter_bytes, term_bytes, cancellation)."""
    out = []
    for name, s in fit_summaries(wl.shop_coarse(spark, d), wl.coarse_attrs(), 300, sweeps=3).items():
        z, b = s.model.size(), s.storage()
        out.append((name, int(z["terms"]), int(z["factors"]), int(z["variables"]), z["log10_monomials"], b["parameters"], b["terms"], s.model.cancellation() if s.model.families else 1.0))
    return spark.createDataFrame(out, "summary string, terms int, factors int, variables int, log10_monomials double, parameter_bytes long, term_bytes long, cancellation double")


@query()
def model_tables(spark, d):
    """Terms of a fitted model with the masks that evaluation skips by."""
    s = summarise(wl.shop_coarse(spark, d), wl.coarse_attrs(), [wl.PAIRS[1], wl.PAIRS[2]], per_pair=30, max_sweeps=5)
    factors = factor_frame(spark, s.model).groupBy("comp_id").agg(F.count(F.lit(1)).alias("factors"))
    terms = term_frame(spark, s.model).groupBy("comp_id", "set_mask").agg(F.count(F.lit(1)).alias("terms"), F.sum("value").alias("value"))
    return terms.join(factors, "comp_id")


@query()
def solver_comparison(spark, d):
    """(method, sweep, residual): block, coordinate and gradient steps from the same start."""
    rel = wl.shop_coarse(spark, d)
    attrs = [Attr("p_brand"), Attr("p_size"), Attr("p_type")]
    base = summarise(rel, attrs, [wl.PAIRS[1], wl.PAIRS[2]], per_pair=20, fit=False)
    rows = []
    for method, sweeps in (("block", 12), ("coordinate", 12), ("gradient", 12)):
        m = Model(base.model.values, base.model.families, base.model.n).solve(method=method, max_sweeps=sweeps, tol=1e-9)
        worst: dict[int, float] = {}
        for sweep, _, r in m.history:
            worst[sweep] = max(worst.get(sweep, 0.0), r)
        rows += [(method, k, v) for k, v in worst.items()]
    return spark.createDataFrame(rows, "method string, sweep int, residual double")


@query()
def other_relations(spark, d):
    """(relation, attrs, groups, error): two-attribute groups of the other tables from a summary with that pair."""
    rows = []
    for name, rel, attrs in (
        ("doc_rel", wl.doc_rel(spark, d), [Attr("lang"), Attr("source"), Attr("logchars", 1, 0, 24), Attr("quality")]),
        ("talk_rel", wl.talk_rel(spark, d), [Attr("role"), Attr("turn", 1, 0, 16), Attr("loglen", 1, 0, 16)]),
        ("page_rel", wl.page_rel(spark, d), [Attr("html_lang"), Attr("scheme"), Attr("suffix")]),
        ("point_rel", wl.point_rel(spark, d), [Attr("label"), Attr("e0", 1, 0, 43), Attr("e1", 1, 0, 43), Attr("e2", 1, 0, 43)]),
        ("event_rel", wl.event_rel(spark, d).select("hour", "event_type", "bucket", "k"), [Attr("hour", 1, 0, 24), Attr("event_type"), Attr("bucket", 1, 0, 200), Attr("k", 1, 0, 100)]),
    ):
        s = summarise(rel, attrs, "cover", n_pairs=1, per_pair=60, max_sweeps=30)
        pair = list(s.pairs[0])
        est = s.group_array(pair)
        codes, _ = encode(rel, attrs, s.domain)
        truth = np.zeros_like(est)
        for r in codes.groupBy(*pair).agg(F.count(F.lit(1)).alias("n")).collect():
            truth[r[pair[0]], r[pair[1]]] = r["n"]
        e = np.where(truth > 0, np.abs(truth - est) / np.maximum(truth + est, 1e-300), 0)[truth > 0]
        rows.append((name, ",".join(pair), int((truth > 0).sum()), float(e.mean()) if len(e) else 0.0))
    return spark.createDataFrame(rows, "relation string, attrs string, groups int, error double")
