"""Answers that a small model must give exactly, or in closed form, so that SQL can check them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from probsum.functions import domain as dom
from probsum.functions.domain import Attr
from probsum.operators import joins, ordering, pairs, rectangles
from probsum.plans import groups, infer
from probsum.plans.forest import build_model
from probsum.plans.model import Family, Model
from probsum.plans.summary import Summary, collect_counts, family_of_sets
from probsum.queries import query
from probsum.queries.methods import _NETGROSS, _nation_models
from probsum.sources import workloads as wl
from probsum.sources.tables import table
from probsum.streaming.updates import Maintained, RebuildPolicy, as_delta

_FLAGS = ["l_returnflag", "l_linestatus"]


def _flag_counts(spark, d):
    return collect_counts(table(spark, d, "lineitem"), [Attr(a) for a in _FLAGS])


def _full_pair(counts, a: str, b: str) -> Family:
    """Every cell of a pair, the empty ones too."""
    m = np.zeros((counts.sizes[a], counts.sizes[b]))
    for r in counts.table.where((F.col("a") == a) & (F.col("b") == b)).collect():  # as many rows as cells
        m[r["x"], r["y"]] = r["n"]
    x, y = (z.ravel() for z in np.indices(m.shape))
    return Family((a, b), {a: np.eye(m.shape[0], dtype=bool)[x], b: np.eye(m.shape[1], dtype=bool)[y]}, m.ravel())


def _codes(counts, attr: str) -> dict[str, int]:
    return {r["label"]: r["code"] for r in counts.domain.where(F.col("attr") == attr).collect()}  # a row a value


_R_F = "count(*) filter (l_returnflag = 'R' and l_linestatus = 'F')"


@query(f"select m as method, {_R_F}::double as est from lineitem, (values ('mask'), ('points'), ('extend'), ('eliminate'), ('derivative'), ('forest')) v(m) group by 1")
def query_strategies(spark, d):
    """One query by every way of asking, on a model that holds the whole pair."""
    c = _flag_counts(spark, d)
    fam = _full_pair(c, *_FLAGS)
    m = Model(c.values, [fam], c.n).solve(max_sweeps=300, tol=1e-9)
    w = {a: infer.mask(m, a, [_codes(c, a)[v]]) for a, v in zip(_FLAGS, "RF")}
    rows = [(k, infer.estimate(m, w, k)) for k in ("mask", "points", "extend", "eliminate", "derivative")]
    forest = build_model(c.values, [fam], c.n, max_terms=1).solve(max_sweeps=300, tol=1e-9)
    rows.append(("forest", infer.estimate(forest, w)))
    return spark.createDataFrame([(k, float(round(e, 3))) for k, e in rows], "method string, est double")


@query("""select count(distinct l_returnflag) * count(distinct l_linestatus) as monomials, count(*)::double as n from lineitem""")
def expanded_polynomial(spark, d):
    """Monomials of the expanded polynomial; its value and the factorised one give the same total estimate."""
    c = _flag_counts(spark, d)
    m = Model(c.values, [_full_pair(c, *_FLAGS)], c.n).solve(max_sweeps=100)
    tuples, w = infer.expand(m)
    return spark.createDataFrame([(len(tuples), round(c.n * float(w.sum()) / m.evaluate(), 6))], "monomials long, n double")


@query("""with n as (select r_regionkey % 2 as a, r_regionkey % 3 as b from region) select 1.0::double as ratio, (select count(distinct a) from n) * (select count(distinct b) from n) as tuples""")
def possible_worlds(spark, d):
    """Sum over all instances of five rows, relative to the n-th power of the polynomial."""
    r = table(spark, d, "region").select(F.expr("cast(r_regionkey % 2 as int)").alias("a"), F.expr("cast(r_regionkey % 3 as int)").alias("b"))
    c = collect_counts(r, [Attr("a"), Attr("b")])
    m = Model(c.values).solve()
    return spark.createDataFrame([(round(infer.worlds_partition(m) / m.evaluate() ** c.n, 9), int(np.prod(list(c.sizes.values()))))], "ratio double, tuples long")


_P = "(select sum(-n * ln(n::double / t)) from (select count(*) as n, sum(count(*)) over () as t from lineitem group by {}))"


@query(f"select round({_P.format('l_returnflag')} + {_P.format('l_linestatus')}, 3) as entropy")
def model_entropy(spark, d):
    """Entropy of the model of single attributes: n times the sum of the attributes' entropies."""
    m = Model(_flag_counts(spark, d).values).solve()
    return spark.createDataFrame([(round(infer.entropy(m), 3),)], "entropy double")


@query("select l_returnflag as flag, count(*)::double as est, round(count(*) * (1 - count(*) / t), 4) as var from lineitem, (select count(*)::double as t from lineitem) group by l_returnflag, t")
def estimate_variance(spark, d):
    """Expected count and its variance, n p (1 - p), of every value."""
    c = _flag_counts(spark, d)
    m = Model(c.values).solve()
    rows = [(v, {_FLAGS[0]: infer.mask(m, _FLAGS[0], [k])}) for v, k in _codes(c, _FLAGS[0]).items()]
    return spark.createDataFrame([(v, round(infer.estimate(m, w), 6), round(infer.variance(m, w), 4)) for v, w in rows], "flag string, est double, var double")


@query("""with t as (select count(*)::double as t from lineitem), a as (select l_returnflag as k, count(*) / t as p from lineitem, t group by 1, t), b as (select l_linestatus as k, count(*) / t as p from lineitem, t group by 1, t),
c as (select l_returnflag as x, l_linestatus as y, count(*) as n from lineitem group by all) select round(sum(n * (ln(a.p) + ln(b.p))), 2) as log_p from c join a on a.k = x join b on b.k = y""")
def instance_probability(spark, d):
    """Log-probability of the instance at hand under the model of single attributes."""
    c = _flag_counts(spark, d)
    m = Model(c.values).solve()
    cells = {(r["x"], r["y"]): r["n"] for r in c.table.collect()}  # as many rows as cells
    return spark.createDataFrame([(round(infer.log_probability(m, cells), 2),)], "log_p double")


@query("select 'R' as flag, round(a * b / t, 4) as est from (select count(*)::double as t, count(*) filter (l_returnflag = 'R') as a, count(*) filter (l_linestatus = 'F') as b from lineitem)")
def summary_from_histograms(spark, d):
    """A summary made of histograms alone answers with the product of frequencies."""
    c = _flag_counts(spark, d)
    s = Summary.from_histograms(spark, c.values).solve()
    flag, status = (_codes(c, a)[v] for a, v in zip(_FLAGS, "RF"))
    return spark.createDataFrame([("R", round(s.count({_FLAGS[0]: f"{_FLAGS[0]} = {flag}", _FLAGS[1]: f"{_FLAGS[1]} = {status}"}), 4))], "flag string, est double")


@query(f"""with b as (select gross, count(*) as n, gross * 1300.0 as lo from {wl.COARSE_SQL} group by all)
select round(sum(n * greatest(0, least(lo + 1300, 30000) - greatest(lo, 10000)) / 1300), 4) as est from b""")
def range_cuts_buckets(spark, d):
    """A range that cuts buckets takes a share of each."""
    c = collect_counts(wl.shop_coarse(spark, d), [Attr("gross", 1, 0, 81)])  # buckets of 1300
    m = Model(c.values).solve()
    w = np.zeros(c.sizes["gross"])
    for k, share in dom.bucket_weights(c.domain, "gross", 10000 / 1300, 30000 / 1300).items():
        w[k] = share
    return spark.createDataFrame([(round(float(infer.estimate(m, {"gross": w})), 4),)], "est double")


_RECTS = ((0, 9, 0, 12), (10, 61, 0, 12), (0, 29, 13, 80), (30, 61, 13, 80))


@query(f"select id, coalesce(sum(n), 0)::double as est from (values {', '.join(str((i, *r)) for i, r in enumerate(_RECTS))}) l(id, x0, x1, y0, y1) left join {_NETGROSS} on x between x0 and x1 and y between y0 and y1 group by 1")
def recover_rectangles(spark, d):
    """The counts of rectangles that the model was given, out of the fitted model."""
    c = collect_counts(wl.shop_coarse(spark, d), [Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)])
    sets = [{"net": set(range(x0, x1 + 1)), "gross": set(range(y0, y1 + 1))} for x0, x1, y0, y1 in _RECTS]
    m = np.zeros((62, 81))
    for r in c.table.collect():  # as many rows as cells
        m[r["x"], r["y"]] = r["n"]
    fam = family_of_sets(sets, [m[x0 : x1 + 1, y0 : y1 + 1].sum() for x0, x1, y0, y1 in _RECTS], c.sizes)
    model = Model(c.values, [fam], c.n).solve(max_sweeps=3000, tol=1e-5)
    est = [infer.estimate(model, {a: infer.mask(model, a, s[a]) for a in s}) for s in sets]
    return spark.createDataFrame([(i, float(round(e, 1))) for i, e in enumerate(est)], "id int, est double")


@query("select count(*) filter (l_returnflag in ('A', 'N') and l_linestatus = 'F' and l_tax < 0.04)::double as est from lineitem")
def recover_three_attributes(spark, d):
    """A statistic over three attributes, out of the fitted model."""
    rel = table(spark, d, "lineitem").selectExpr("l_returnflag", "l_linestatus", "cast(round(l_tax * 100) as int) as tax")
    c = collect_counts(rel, [Attr("l_returnflag"), Attr("l_linestatus"), Attr("tax")])
    at = {a: _codes(c, a) for a in ("l_returnflag", "l_linestatus", "tax")}
    rect = {"l_returnflag": {at["l_returnflag"][v] for v in "AN"}, "l_linestatus": {at["l_linestatus"]["F"]}, "tax": {k for v, k in at["tax"].items() if int(v) < 4}}
    n = rel.where("l_returnflag in ('A', 'N') and l_linestatus = 'F' and tax < 4").count()
    m = Model(c.values, [family_of_sets([rect], [float(n)], c.sizes)], c.n).solve(max_sweeps=2000, tol=1e-6)
    return spark.createDataFrame([(round(infer.estimate(m, {a: infer.mask(m, a, s) for a, s in rect.items()}), 2),)], "est double")


#: Pairs of lineitem's attributes, and the widths of the blocks of codes that their rectangles are.
_BLOCKS = (("a", 10, "b", 3), ("b", 4, "c", 3), ("c", 2, "d", 2))
_BLOCK_CODES = {"a": "cast(l_quantity as int) - 1", "b": "cast(round(l_discount * 100) as int)", "c": "cast(round(l_tax * 100) as int)", "d": "cast(l_linenumber as int) - 1"}
_BLOCK_SIZES = {"a": 50, "b": 11, "c": 9, "d": 7}
_BLOCK_SQL = ", ".join(
    f"{x}{y} as (select x * {u} as l0, x * {u} + {u - 1} as l1, y * {v} as r0, y * {v} + {v - 1} as r1 from (select {x} // {u} as x, {y} // {v} as y, count(*) as n from v group by 1, 2 order by n desc, 1, 2 limit 5))"
    for x, u, y, v in _BLOCKS
)


@query(f"""with v as (select {", ".join(f"{e} as {k}" for k, e in _BLOCK_CODES.items())} from lineitem), {_BLOCK_SQL},
j as (select 2 as members, count(*) as n from ab, bc where ab.r0 <= bc.l1 and bc.l0 <= ab.r1 union all select 2, count(*) from bc, cd where bc.r0 <= cd.l1 and cd.l0 <= bc.r1 union all select 2, count(*) from ab, cd
union all select 3, count(*) from ab, bc, cd where ab.r0 <= bc.l1 and bc.l0 <= ab.r1 and bc.r0 <= cd.l1 and cd.l0 <= bc.r1)
select mode, members, sum(n)::bigint as n from j, (values ('levelwise'), ('per_subset'), ('outer_once')) m(mode) group by all""")
def compatible_groups(spark, d):
    """Groups of rectangles that meet, the five fullest blocks of each pair, by each of the three joins, beside SQL on interval ends."""
    codes = table(spark, d, "lineitem").select(*[F.expr(e).alias(k) for k, e in _BLOCK_CODES.items()])
    fams = []
    for a, u, b, v in _BLOCKS:
        blocks = codes.groupBy(F.expr(f"{a} div {u}").alias("x"), F.expr(f"{b} div {v}").alias("y")).agg(F.count(F.lit(1)).alias("n"))
        top = blocks.orderBy(F.desc("n"), "x", "y").limit(5).collect()
        sets = [
            {k: set(range(r[i] * w, min((r[i] + 1) * w, _BLOCK_SIZES[k]))) for k, i, w in ((a, "x", u), (b, "y", v))} for r in top
        ]
        fams.append(family_of_sets(sets, [float(r["n"]) for r in top], _BLOCK_SIZES))
    rects = groups.rect_frame(spark, fams)
    out = None
    for mode in ("levelwise", "per_subset", "outer_once"):
        got = groups.compatible_groups(rects, [0, 1, 2], mode).groupBy(F.size("members").alias("members")).agg(F.count(F.lit(1)).alias("n"))
        got = got.select(F.lit(mode).alias("mode"), "members", "n")
        out = got if out is None else out.union(got)
    return out


def _best_cut_sql(axis: str, size: int, other: int) -> str:
    return f"""(with m as (select {axis} as k, sum(n) as s, sum(n * n) as q from {_NETGROSS} where x < 62 and y < 81 group by 1),
c as (select unnest(range(1, {size})) as cut), e as (select cut, sum(q)::double - pow(coalesce(sum(s) filter (k < cut), 0), 2) / (cut * {other}.0) - pow(coalesce(sum(s) filter (k >= cut), 0), 2) / (({size} - cut) * {other}.0) as sse from c, m group by 1)
select '{axis}' as axis, cut::int as cut, round(sse, 1) as sse from e order by sse, cut limit 1)"""


@query(f"{_best_cut_sql('x', 62, 81)} union all {_best_cut_sql('y', 81, 62)}")
def best_cuts(spark, d):
    """The cut of least squared error along each axis of the pair, and that error."""
    c = collect_counts(wl.shop_coarse(spark, d), [Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)])
    m = np.zeros((62, 81))
    for r in c.table.collect():  # as many rows as cells
        m[r["x"], r["y"]] = r["n"]
    pre = rectangles.Prefix(m)
    rows = [(k, *rectangles.best_split(pre, (0, 62, 0, 81), i)) for i, k in enumerate("xy")]
    return spark.createDataFrame([(k, int(cut), round(float(e), 1)) for k, e, cut in rows], "axis string, cut int, sse double")


@query("select sum(a.n * a.n)::double as est from (select count(*) as n from customer group by c_nationkey, c_mktsegment) a")
def join_composite_key(spark, d):
    """A join on two attributes from models that hold their pair."""
    m, _, segments = _nation_models(spark, d)
    x, y = (z.ravel() for z in np.indices(m.shape))
    fam = Family(("nation", "segment"), {"nation": np.eye(25, dtype=bool)[x], "segment": np.eye(len(segments), dtype=bool)[y]}, m.ravel())
    model = Model({"nation": m.sum(axis=1), "segment": m.sum(axis=0)}, [fam]).solve(max_sweeps=500, tol=1e-9)
    return spark.createDataFrame([(round(joins.estimate_join([model, model], [["nation", "segment"]]), 2),)], "est double")


@query("""with c as (select c_nationkey as k, count(*) as n from customer group by 1), s as (select s_nationkey as k, count(*) as n from supplier group by 1)
select 'whole' as chain, sum(s.n * c.n * s.n)::double as est from c join s using (k) union all select 'first two', sum(s.n * c.n) from c join s using (k) union all select 'last two', sum(c.n * s.n) from c join s using (k)""")
def join_sub_chains(spark, d):
    """A chain of three relations and its parts."""
    m, supplier, _ = _nation_models(spark, d)
    s, c = Model({"nation": supplier}).solve(), Model({"nation": m.sum(axis=1)}).solve()
    keys = [["nation"], ["nation"]]
    rows = [("whole", range(0, 3)), ("first two", range(0, 2)), ("last two", range(1, 3))]
    return spark.createDataFrame([(k, round(joins.estimate_join([s, c, s], keys, used=u), 4)) for k, u in rows], "chain string, est double")


@query("select 'refused' as shortened, sum(a.n * b.n)::double as est from (select c_nationkey as k, count(*) as n from customer group by 1) a join (select s_nationkey as k, count(*) as n from supplier group by 1) b using (k)")
def join_mismatched_boundaries(spark, d):
    """Boundaries that differ: the shortened sum is refused, and the full one is right."""
    m, supplier, _ = _nation_models(spark, d)
    left, right = Model({"nation": m.sum(axis=1)}).solve(), Model({"nation": supplier}).solve()
    try:
        joins.estimate_join_grouped(left, right, "nation", joins.key_cuts(m, 5))
        said = "taken"
    except ValueError:
        said = "refused"
    return spark.createDataFrame([(said, round(joins.estimate_join([left, right], [["nation"]]), 4))], "shortened string, est double")


_NEW = "(select o_orderstatus, o_orderpriority from orders where o_orderkey % 10 = 0)"


@query(f"""select 'pending' as what, count(*)::double as n from {_NEW} union all select 'unknown', count(*) from {_NEW} where o_orderstatus = 'F' union all select 'reason: unknown values', 1
union all select 'reason: updates', 1 union all select 'rebuilt', (select count(*) from orders) + (select count(*) from {_NEW}) union all select 'rebuilt domain', (select count(distinct o_orderstatus) + 1 from orders)""")
def rebuild_triggers(spark, d):
    """Inserts of which some lie outside the pinned domain: what is pending, what calls for a rebuild, and the rebuild."""
    rel = table(spark, d, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority")
    attrs = [Attr("o_orderstatus"), Attr("o_orderpriority")]
    old = rel.select("o_orderstatus", "o_orderpriority")
    c = collect_counts(old, attrs)
    kept = Maintained(Summary(spark, c.domain, Model(c.values, n=c.n), attrs).solve())
    new = rel.where("o_orderkey % 10 = 0").selectExpr("if(o_orderstatus = 'F', 'X', o_orderstatus) as o_orderstatus", "o_orderpriority")
    kept.apply_delta(as_delta(None, new))
    known = kept.pending.n
    rows = [("pending", float(known + kept.pending.unknown)), ("unknown", float(kept.pending.unknown))]
    rows += [(f"reason: {r}", 1.0) for r in RebuildPolicy(max_updates=1).reasons(kept)]
    s = kept.rebuild(old.union(new), n_pairs=0)
    rows += [("rebuilt", float(s.model.n)), ("rebuilt domain", float(s.model.sizes["o_orderstatus"]))]
    return spark.createDataFrame(rows, "what string, n double")


@query("""with b as (select l_returnflag as flag, count(*) // 100 as total from lineitem group by 1)
select flag, total::int as total, pairs, (total // pairs)::int as per_pair from b, (values (2), (3), (5)) v(pairs)""")
def budget_rule(spark, d):
    """Statistics of a pair under a total budget of one a hundred rows of each return flag."""
    found = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n")).collect()  # a row a flag
    rows = [(r["l_returnflag"], r["n"] // 100, p, pairs.Budget(r["n"] // 100, p).per_pair) for r in found for p in (2, 3, 5)]
    return spark.createDataFrame(rows, "flag string, total int, pairs int, per_pair int")


@query(f"select kind, cells, true as permuted, true as settled from (values ('natural'), ('zero_index'), ('one_index'), ('weighted_index')) v(kind), (select (count(distinct x) * count(distinct y))::int as cells from {_NETGROSS})")
def ordering_kinds(spark, d):
    """Every ordering gives a permutation of both axes of (net, gross), shuffled, and a second pass over its result changes nothing."""
    c = collect_counts(wl.shop_coarse(spark, d), [Attr("net"), Attr("gross")])
    m = np.zeros((c.sizes["net"], c.sizes["gross"]), dtype=np.int64)
    for r in c.table.collect():  # as many rows as cells
        m[r["x"], r["y"]] = r["n"]
    m = ordering.shuffled(m, 3)
    rows = []
    for kind in ordering.KINDS:
        x, y = ordering.order_axes(m, kind)
        done = m[np.ix_(x, y)]
        x2, y2 = ordering.order_axes(done, kind)
        permuted = sorted(x) == list(range(len(m))) and sorted(y) == list(range(m.shape[1]))
        rows.append((kind, done.size, permuted, bool((done[np.ix_(x2, y2)] == done).all())))
    return spark.createDataFrame(rows, "kind string, cells int, permuted boolean, settled boolean")
