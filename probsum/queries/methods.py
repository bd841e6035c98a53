"""The paper's methods on the given tables: domains, statistics, pair and rectangle choice, models, estimates, joins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from probsum.functions import domain as dom
from probsum.functions import metrics
from probsum.functions.domain import Attr
from probsum.operators import joins, ordering, pairs, rectangles, samples, stats
from probsum.plans import costs, infer
from probsum.plans.model import Family, Model
from probsum.plans.summary import Summary, collect_counts, summarise
from probsum.queries import query
from probsum.sources import workloads as wl
from probsum.sources.tables import SummarySource, model_option, register_udtf, scratch, table

_C = wl.COARSE_SQL
_NETGROSS = f"(select net as x, gross as y, count(*) as n from {_C} group by 1, 2)"
_BRAND = "(select p_brand as v, (row_number() over (order by p_brand) - 1)::int as code from (select distinct p_brand from part join lineitem on l_partkey = p_partkey))"


def _coarse_codes(spark, d):
    return dom.encode(wl.shop_coarse(spark, d), wl.coarse_attrs())


# -- domains -------------------------------------------------------------------------


@query(f"select ship_month::int as ship_month, net, gross, count(*) as n from {_C} group by all")
def domain_buckets(spark, d):
    return wl.shop_coarse(spark, d).groupBy("ship_month", "net", "gross").agg(F.count(F.lit(1)).alias("n"))


@query("""with b as (select p_brand, p_name, count(*) as n from lineitem join part on l_partkey = p_partkey group by all),
t as (select p_brand, p_name from b qualify row_number() over (partition by p_brand order by n desc, p_name) <= 2)
select p.p_brand || '|' || case when t.p_name is null then 'Other' else p.p_name end as brand_name, count(*) as n
from lineitem join part p on l_partkey = p_partkey left join t on t.p_brand = p.p_brand and t.p_name = p.p_name group by 1""")
def domain_top2_other(spark, d):
    return wl.shop_fine(spark, d).groupBy("brand_name").agg(F.count(F.lit(1)).alias("n"))


@query(f"select attr, size, round(sum(log10(size)) over (), 6) as log10_d from (values ('ship_month', 83), ('net', 62), ('gross', 81), ('p_brand', (select count(distinct p_brand) from {_C})), ('p_size', (select count(distinct p_size) from {_C})), ('p_type', (select count(distinct p_type) from {_C}))) t(attr, size)")
def domain_sizes(spark, d):
    _, domain = _coarse_codes(spark, d)
    return dom.domain_report(domain).select("attr", "size", F.round("log10_d", 6).alias("log10_d"))


@query("select count(*) as n, count(quality) as labelled from documents left join labels using (doc_id)")
def domain_nulls(spark, d):
    rel = wl.doc_rel(spark, d)
    return rel.agg(F.count(F.lit(1)).alias("n")).crossJoin(dom.drop_nulls(rel, ["quality"]).agg(F.count(F.lit(1)).alias("labelled")))


@query("select datediff('day', date '1995-01-01', o_orderdate::date)::int as day, floor(datediff('day', date '1995-01-01', o_orderdate::date) / 7)::int as week, (year(o_orderdate) - 1995)::int as year, floor((year(o_orderdate) - 1995) * 12 / 36.0)::int as era, count(*) as n from orders group by all")
def domain_dates(spark, d):
    o = table(spark, d, "orders")
    cols = [dom.date_code("o_orderdate", u, "1995-01-01").alias(u) for u in ("day", "week", "year", "era")]
    return o.select(*cols).groupBy("day", "week", "year", "era").agg(F.count(F.lit(1)).alias("n"))


@query(f"select v as label, code, count(*) as n from {_C} join {_BRAND} b on p_brand = v group by all")
def domain_encode(spark, d):
    codes, domain = _coarse_codes(spark, d)
    names = domain.where("attr = 'p_brand'").select("label", F.col("code").alias("c2"))
    return codes.groupBy(F.col("p_brand").alias("code")).agg(F.count(F.lit(1)).alias("n")).join(names, F.expr("code = c2")).select("label", "code", "n")


# -- statistics ----------------------------------------------------------------------


@query(f"""select 'ship_month' as attr, ship_month::int as code, count(*) as n from {_C} group by all union all select 'p_size', p_size - 1, count(*) from {_C} group by all
union all select 'net', net, count(*) from {_C} group by all union all select 'gross', gross, count(*) from {_C} group by all""")
def stat_values(spark, d):
    rows = wl.shop_coarse(spark, d).select("ship_month", (F.col("p_size") - 1).alias("p_size"), "net", "gross")
    return stats.value_stats(stats.base_cuboid(rows))


@query(f"""select 'net' as a, 'gross' as b, net as x, gross as y, count(*) as n from {_C} group by all union all
select 'p_size' as a, 'net' as b, p_size - 1 as x, net as y, count(*) as n from {_C} group by all""")
def stat_contingency(spark, d):
    rows = wl.shop_coarse(spark, d).select((F.col("p_size") - 1).alias("p_size"), "net", "gross")
    return stats.contingencies(stats.base_cuboid(rows), [("net", "gross"), ("p_size", "net")])


@query(f"select ship_month::int as ship_month, p_brand, p_size, p_type, net, gross, count(*) as n from {_C} group by all")
def stat_cuboid(spark, d):
    return stats.base_cuboid(wl.shop_coarse(spark, d))


@query(f"""select 'heavy' as stat, count(*) filter (net between 10 and 19 and gross between 13 and 25) as n from {_C} union all
select 'point', count(*) filter (p_size = 7) from {_C} union all select 'cube', count(*) filter (net < 20 and p_size > 10 and p_type = 'STANDARD') from {_C}""")
def stat_predicates(spark, d):
    return stats.predicate_stats(
        wl.shop_coarse(spark, d),
        {"heavy": "net between 10 and 19 and gross between 13 and 25", "point": "p_size = 7", "cube": "net < 20 and p_size > 10 and p_type = 'STANDARD'"},
    )


@query(f"select leaf_id, coalesce(sum(n), 0)::bigint as n from (values (0, 0, 9, 0, 12), (1, 10, 61, 0, 12), (2, 0, 61, 13, 80)) l(leaf_id, x0, x1, y0, y1) left join {_NETGROSS} on x between x0 and x1 and y between y0 and y1 group by 1")
def stat_rectangles(spark, d):
    leaves = spark.createDataFrame([(0, 0, 9, 0, 12), (1, 10, 61, 0, 12), (2, 0, 61, 13, 80)], "leaf_id int, x0 int, x1 int, y0 int, y1 int")
    leaves = leaves.selectExpr("leaf_id", "sequence(x0, x1) as x_codes", "sequence(y0, y1) as y_codes")
    return stats.rect_targets(_cells(spark, d), leaves)


def _cells(spark, d, a="net", b="gross"):
    return wl.shop_coarse(spark, d).groupBy(F.col(a).alias("x"), F.col(b).alias("y")).agg(F.count(F.lit(1)).alias("n"))


# -- pairs and rectangles -------------------------------------------------------------

_PAIRLIST = [("p_brand", "p_size"), ("p_brand", "p_type"), ("p_size", "p_type"), ("net", "gross"), ("ship_month", "gross")]


def _chi2_sql(a, b):
    return f"""select '{a}' as a, '{b}' as b, round(t * (sum(n::double * n / (nx::double * ny)) - 1), 4) as chi2, ((max(r) - 1) * (max(c) - 1))::bigint as df
from (select n, sum(n) over (partition by x) as nx, sum(n) over (partition by y) as ny, sum(n) over () as t, count(distinct x) over () as r, count(distinct y) over () as c
from (select {a} as x, {b} as y, count(*) as n from {_C} group by 1, 2)) group by t"""


@query(" union all ".join(_chi2_sql(a, b) for a, b in _PAIRLIST))
def pair_chi2(spark, d):
    counts = collect_counts(wl.shop_coarse(spark, d), wl.coarse_attrs(), _PAIRLIST)
    scored = pairs.pair_scores(counts.table, counts.n)
    return scored.select("a", "b", F.round("chi2", 4).alias("chi2"), "df")


@query()
def pair_policies(spark, d):
    """(relation, policy, a, b): what each policy picks on the relation where they differ, the date left out."""
    attrs = [Attr("ship_month", 1, 0, 83), Attr("p_brand"), Attr("p_size"), Attr("p_type"), Attr("c_nationkey"), Attr("c_mktsegment")]
    counts = collect_counts(wl.shop_mix(spark, d), attrs)
    scored = pairs.pair_scores(counts.table, counts.n).collect()
    counts.release()
    rows = []
    for policy in ("correlation", "cover", "mi_tree"):
        given = [(r["a"], r["b"], r["mi" if policy == "mi_tree" else "chi2"]) for r in scored]
        rows += [("shop_mix", policy, a, b) for a, b in pairs.pick_pairs(given, 2, policy, exclude=("ship_month",))]
    return spark.createDataFrame(rows, "relation string, policy string, a string, b string")


@query(f"select x, y, n from {_NETGROSS} order by n desc, x, y limit 40")
def rect_heavy(spark, d):
    return rectangles.heavy_cells(_cells(spark, d), 40)


@query(f"select x, y, n from (select a.range::int as x, b.range::int as y, 0::bigint as n from range(62) a, range(81) b where (a.range, b.range) not in (select (x, y) from {_NETGROSS}) order by 1, 2 limit 100)")
def rect_empty(spark, d):
    x, y = spark.range(62).selectExpr("cast(id as int) as x"), spark.range(81).selectExpr("cast(id as int) as y")
    return rectangles.empty_cells(_cells(spark, d), x, y, 100)


@query(f"""select leaf_id, round(sqrt(greatest(sum(q) - sum(n) * sum(n) / count(*), 0)), 4) as error from (select leaf_id, coalesce(n, 0)::double as n, coalesce(n, 0)::double * coalesce(n, 0) as q from
(select a.range::int as x, b.range::int as y from range(62) a, range(81) b) g left join {_NETGROSS} c using (x, y)
join (values (0, 0, 9, 0, 12), (1, 10, 61, 0, 12), (2, 0, 61, 13, 80)) l(leaf_id, x0, x1, y0, y1) on x between x0 and x1 and y between y0 and y1) group by 1""")
def rect_kd_error(spark, d):
    """Root squared error of given leaves, from the dense matrix."""
    m = np.zeros((62, 81), dtype=np.int64)
    for r in _cells(spark, d).collect():  # at most 62 x 81 cells
        m[r["x"], r["y"]] = r["n"]
    rows = []
    for i, (a, b, c, e) in enumerate([(0, 9, 0, 12), (10, 61, 0, 12), (0, 61, 13, 80)]):
        leaf = rectangles.Leaf(tuple(range(a, b + 1)), tuple(range(c, e + 1)), 0, 0.0)
        rows.append((i, round(rectangles.kd_error(m, [leaf]), 4)))
    return spark.createDataFrame(rows, "leaf_id int, error double")


@query()
def udf_kd(spark, d):
    """K-D rectangles of three pairs, one task per pair."""
    codes, domain = _coarse_codes(spark, d)
    sizes = {r["attr"]: r["s"] for r in domain.groupBy("attr").agg((F.max("code") + 1).alias("s")).collect()}
    table_ = stats.contingencies(stats.base_cuboid(codes), [("p_brand", "p_size"), ("p_size", "p_type"), ("net", "gross")])
    return rectangles.kd_for_pairs(table_, sizes, 60, "natural").select("a", "b", "leaf_id", "n", "sse", F.size("x_codes").alias("width"), F.size("y_codes").alias("height"))


def _order_sql(kind):
    if kind == "zero_index":
        score = f"select a.range::int as x, avg((b.range + 1)::double) as s from range(62) a, range(81) b where (a.range, b.range) not in (select (x, y) from {_NETGROSS}) group by 1"
    else:
        score = f"select x, sum((y + 1) * n)::double as s from {_NETGROSS} group by 1"
    return f"select x, (row_number() over (order by s, x) - 1)::int as pos from (select r.range::int as x, coalesce(s, 0) as s from range(62) r left join ({score}) on r.range = x)"


for _kind in ("zero_index", "weighted_index"):

    def _pass(spark, d, kind=_kind):
        x, y = spark.range(62).selectExpr("cast(id as int) as x"), spark.range(81).selectExpr("cast(id as int) as y")
        return ordering.ordering_pass(_cells(spark, d), x, y, kind)

    query(_order_sql(_kind), f"order_{_kind}_pass")(_pass)


# -- estimates with closed forms ----------------------------------------------------------


_ATTRS3 = [Attr("p_brand"), Attr("p_size"), Attr("p_type")]
_T = f"(select count(*)::double from {_C})"


def _n(cols):
    return f"(select {', '.join(cols)}, count(*)::double as n from {_C} group by {', '.join(cols)})"


@query(f"select a.p_brand, b.p_type, round(a.n * b.n / {_T}, 6) as est from {_n(['p_brand'])} a, {_n(['p_type'])} b")
def est_1d_product(spark, d):
    """No two-dimensional statistics: the product of frequencies."""
    s = summarise(wl.shop_coarse(spark, d), _ATTRS3, n_pairs=0)
    return s.groups(["p_brand", "p_type"]).select("p_brand", "p_type", F.round("est", 6).alias("est"))


def _full_pairs(spark, d, attrs, pair_list, by, sweeps=400):
    """A summary whose pairs are tabulated cell by cell."""
    s = summarise(wl.shop_coarse(spark, d), attrs, pair_list, per_pair=10**9, rects="heavy", max_sweeps=sweeps, tol=1e-9)
    return s.groups(by)


@query(f"select a.p_brand, a.p_type, b.p_size::varchar as p_size, round(a.n * b.n / {_T}, 5) as est from {_n(['p_brand', 'p_type'])} a, {_n(['p_size'])} b")
def est_pair_full(spark, d):
    """One pair with all its cells: n_ab n_c / n."""
    return _full_pairs(spark, d, _ATTRS3, [("p_brand", "p_type")], ["p_brand", "p_type", "p_size"]).where("est > 1e-9").select(
        "p_brand", "p_type", "p_size", F.round("est", 5).alias("est")
    )


@query(f"select a.p_brand, a.p_type, b.grp, round(a.n * b.n / c.n, 5) as est from {_n(['p_brand', 'p_type'])} a join (select p_type, least(gross // 9, 8)::int as grp, count(*)::double as n from {_C} group by 1, 2) b on a.p_type = b.p_type join {_n(['p_type'])} c on a.p_type = c.p_type")
def est_chain_full(spark, d):
    """Two pairs that share an attribute: n_ab n_bc / n_b."""
    rel = wl.shop_coarse(spark, d).withColumn("grp", F.least(F.floor(F.col("gross") / 9), F.lit(8)).cast("int"))
    attrs = [Attr("p_brand"), Attr("p_type"), Attr("grp", 1, 0, 9)]
    s = summarise(rel, attrs, [("p_brand", "p_type"), ("p_type", "grp")], per_pair=10**9, rects="heavy", max_sweeps=400, tol=1e-9)
    return s.groups(["p_brand", "p_type", "grp"]).where("est > 1e-9").select("p_brand", "p_type", F.col("grp").cast("int").alias("grp"), F.round("est", 5).alias("est"))


@query(f"select a.p_brand, a.p_type, b.net, round(sum(a.n * b.n) / {_T}, 5) as est from {_n(['p_brand', 'p_type'])} a, (select least(net // 7, 8)::int as net, count(*)::double as n from {_C} group by 1) b group by 1, 2, 3")
def est_disjoint_full(spark, d):
    """Two pairs without a shared attribute: the components multiply, n_ab n_cd / n."""
    rel = wl.shop_coarse(spark, d).withColumn("net", F.least(F.floor(F.col("net") / 7), F.lit(8)).cast("int")).withColumn("gross", F.least(F.floor(F.col("gross") / 9), F.lit(8)).cast("int"))
    attrs = [Attr("p_brand"), Attr("p_type"), Attr("net", 1, 0, 9), Attr("gross", 1, 0, 9)]
    s = summarise(rel, attrs, [("p_brand", "p_type"), ("net", "gross")], per_pair=10**9, rects="heavy", max_sweeps=400, tol=1e-9)
    return s.groups(["p_brand", "p_type", "net"]).where("est > 1e-9").select("p_brand", "p_type", F.col("net").cast("int").alias("net"), F.round("est", 5).alias("est"))


# -- recovered statistics ---------------------------------------------------------------------


def _fitted(spark, d, rects="kd", pair_list=(("p_brand", "p_type"), ("p_size", "p_type")), per_pair=60, sweeps=2000, attrs=None, **options):
    """A summary fitted until every expectation is within 0.01 of its target, or for `sweeps` sweeps."""
    return summarise(wl.shop_coarse(spark, d), attrs or wl.coarse_attrs(), list(pair_list), per_pair=per_pair, rects=rects, max_sweeps=sweeps, tol=0.01, **options)


@query(f"select p_brand, count(*) as n from {_C} group by 1")
def recover_values(spark, d):
    return _fitted(spark, d).groups(["p_brand"]).select("p_brand", F.col("est_rounded").alias("n"))


def _expected_cells(spark, s: Summary, f: int):
    fam = s.model.families[f]
    a, b = fam.attrs
    q, _ = s.model.partial_rects(f)
    est = s.model.n * s.model.delta[f] * q / s.model.evaluate()
    labels = {x: {r["code"]: r["label"] for r in s.domain.where(f"attr = '{x}'").collect()} for x in (a, b)}
    rows = [
        (labels[a][int(np.flatnonzero(fam.masks[a][i])[0])], labels[b][int(np.flatnonzero(fam.masks[b][i])[0])], int(infer.rounded(e)))
        for i, e in enumerate(est)
    ]
    return spark.createDataFrame(rows, f"{a} string, {b} string, n long")


@query(f"select p_brand, p_type, count(*) as n from {_C} group by 1, 2 order by n desc, p_brand, p_type limit 60")
def recover_heavy(spark, d):
    return _expected_cells(spark, _fitted(spark, d, "heavy"), 0)


@query(f"""with c as (select net, gross, count(*) as n from {_C} group by 1, 2), g as (select a.range::int as net, b.range::int as gross, 0::bigint as n from range(62) a, range(81) b
where (a.range, b.range) not in (select (net, gross) from c) order by 1, 2 limit 50) select net::varchar as net, gross::varchar as gross, n from g""")
def recover_empty(spark, d):
    attrs = [Attr("p_type"), Attr("net", 1, 0, 62), Attr("gross", 1, 0, 81)]
    return _expected_cells(spark, _fitted(spark, d, "empty", [("net", "gross")], 50, attrs=attrs), 0)


@query(f"select p_type, count(*) as n from {_C} group by 1")
def recover_kd_margins(spark, d):
    return _fitted(spark, d, "kd").groups(["p_type"]).select("p_type", F.col("est_rounded").alias("n"))


@query(f"select p_brand, count(*) as n from {_C} group by 1 order by count(*) desc, p_brand limit 5")
def est_groups_topk(spark, d):
    return _fitted(spark, d).top(["p_brand"], 5).select("p_brand", F.col("est_rounded").alias("n"))


@query(f"select round(sum(net + 0.5), 0) as total, round(avg(net + 0.5), 4) as mean from {_C}")
def est_sum_1d(spark, d):
    """SUM and AVG by bucket midpoints are exact where the weights are a function of one attribute."""
    s = _fitted(spark, d)
    return spark.createDataFrame([(round(s.sum("net"), 0), round(s.avg("net"), 4))], "total double, mean double")


@query(f"select round(sum(a.n) * (select sum(n) from {_n(['gross'])} where gross >= 20) / {_T}, 4) as est from {_n(['p_size'])} a where p_size between 3 and 9")
def est_filters_1d(spark, d):
    s = summarise(wl.shop_coarse(spark, d), wl.coarse_attrs(), n_pairs=0)
    return spark.createDataFrame([(round(s.count({"p_size": "p_size between 3 and 9", "gross": "gross >= 20"}), 4),)], "est double")


@query(f"with p as (select (select sum(n) from {_n(['p_type'])} where p_type like 'S%') / {_T} as a, (select sum(n) from {_n(['net'])} where net < 9) / {_T} as b) select round({_T} * (a + b - a * b), 4) as est from p")
def est_disjunction_1d(spark, d):
    s = summarise(wl.shop_coarse(spark, d), wl.coarse_attrs(), n_pairs=0)
    return spark.createDataFrame([(round(s.count_any([{"p_type": "p_type like 'S%'"}, {"net": "net < 9"}]), 4),)], "est double")


@query(f"select a.p_type, round(-(exp({_T} * ln(1 - a.n / {_T} * b.n / {_T})) - 1), 9) as p from {_n(['p_type'])} a, {_n(['net'])} b where b.net = 40")
def tuple_probability_1d(spark, d):
    s = summarise(wl.shop_coarse(spark, d), [Attr("p_type"), Attr("net", 1, 0, 62)], n_pairs=0)
    types = [r["label"] for r in s.domain.where("attr = 'p_type'").orderBy("code").collect()]
    rows = [(t, round(s.probability({"p_type": i, "net": 40}), 9)) for i, t in enumerate(types)] if s.model.values["net"][40] > 0 else []
    return spark.createDataFrame(rows, "p_type string, p double")


@query("""with recursive g as (select count(*) filter (l_linestatus = 'F')::double as c1, count(*) filter (l_linestatus <> 'F')::double as c2,
count(*) filter (l_quantity <= 20)::double as r1, count(*) filter (l_quantity > 20)::double as r2 from lineitem),
t(k, a11, a12, a21, a22) as (select 0, 1.0::double, 1.0::double, 1.0::double, 1.0::double union all
select k + 1, r1 * x11 / (x11 + x21) , r2 * x12 / (x12 + x22), r1 * x21 / (x11 + x21), r2 * x22 / (x12 + x22) from
(select k, c1 * a11 / (a11 + a12) as x11, c1 * a12 / (a11 + a12) as x12, c2 * a21 / (a21 + a22) as x21, c2 * a22 / (a21 + a22) as x22, r1, r2 from t, g where k < 5))
select round(a11, 4) as e11, round(a12, 4) as e12, round(a21, 4) as e21, round(a22, 4) as e22 from t where k = 5""")
def ipf_toy(spark, d):
    """Block steps on two attributes are proportional fitting: five sweeps on the lines' status and small or large quantity."""
    at = [(F.col("l_linestatus") == "F").alias("a"), (F.col("l_quantity") <= 20).alias("b")]
    rows = table(spark, d, "lineitem").select(*at).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).collect()
    counts = {c: np.array([float(sum(r["n"] for r in rows if r[c] is x)) for x in (True, False)]) for c in "ab"}
    m = Model(counts).solve(max_sweeps=5)
    e = infer.estimate_groups(m, ["a", "b"]).ravel()
    return spark.createDataFrame([tuple(round(float(x), 4) for x in e)], "e11 double, e12 double, e21 double, e22 double")


@query()
def est_kd_groups(spark, d):
    return _fitted(spark, d, sweeps=30).groups(["p_brand", "p_size"])


# -- joins of summaries --------------------------------------------------------------------------


def _nation_models(spark, d):
    c = table(spark, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n")).collect()
    s = table(spark, d, "supplier").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("n")).collect()
    segments = sorted({r["c_mktsegment"] for r in c})
    matrix = np.zeros((25, len(segments)))
    for r in c:
        matrix[r["c_nationkey"], segments.index(r["c_mktsegment"])] = r["n"]
    supplier = np.zeros(25)
    for r in s:
        supplier[r["s_nationkey"]] = r["n"]
    return matrix, supplier, segments


@query("select sum(a.n * b.n)::double as est from (select c_nationkey as k, count(*) as n from customer group by 1) a join (select s_nationkey as k, count(*) as n from supplier group by 1) b using (k)")
def join_keys_only(spark, d):
    """One-dimensional statistics on the key make the size of the join exact."""
    matrix, supplier, _ = _nation_models(spark, d)
    left = Model({"nation": matrix.sum(axis=1), "segment": matrix.sum(axis=0)}).solve()
    right = Model({"nation": supplier}).solve()
    return spark.createDataFrame([(round(joins.estimate_join([left, right], [["nation"]]), 6),)], "est double")


@query()
def est_join_grouped(spark, d):
    """(method, est): the full sum and the shortened one under shared boundaries, beside the exact size."""
    matrix, supplier, _ = _nation_models(spark, d)
    cuts = joins.key_cuts(matrix, 5)
    left = joins.share_boundaries({"nation": matrix.sum(axis=1), "segment": matrix.sum(axis=0)}, matrix, "nation", "segment", cuts, 20).solve(max_sweeps=100)
    right = Model({"nation": joins.averaged(supplier, cuts)}).solve()
    full = joins.estimate_join([left, right], [["nation"]])
    rows = [("full", full), ("grouped", joins.estimate_join_grouped(left, right, "nation", cuts)), ("exact", float(matrix.sum(axis=1) @ supplier))]
    return spark.createDataFrame(rows, "method string, est double")


@query("select count(*)::double as est from supplier join customer on s_nationkey = c_nationkey join orders on o_custkey = c_custkey")
def join_chain_keys(spark, d):
    """Chain of three relations; the middle one carries the full pair of its two keys.

    Customers of one nation share their boundaries, so a nation's customers are one group of key values: the orders
    of a group count as the mean over its values, and Spark counts groups of customers and of orders by nation.
    """
    orders = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count(F.lit(1)).alias("o"))
    grouped = table(spark, d, "customer").join(orders, "c_custkey", "left").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"), F.sum("o").alias("o"))
    customers, placed = np.zeros(25), np.zeros(25)
    for r in grouped.collect():  # a row a nation
        customers[r["c_nationkey"]], placed[r["c_nationkey"]] = r["n"], r["o"] or 0
    fam = Family(("group", "nation"), {"group": np.eye(25, dtype=bool), "nation": np.eye(25, dtype=bool)}, customers)
    middle = Model({"group": customers, "nation": customers}, [fam]).solve(max_sweeps=60)
    _, supplier, _ = _nation_models(spark, d)
    mean = np.divide(placed, customers, out=np.zeros(25), where=customers > 0)
    est = joins.estimate_join([Model({"nation": supplier}).solve(), middle, Model({"group": mean}).solve()], [["nation"], ["group"]])
    return spark.createDataFrame([(round(est, 3),)], "est double")


@query("select r_name, round(count(*)::double, 3) as est from supplier join nation on s_nationkey = n_nationkey join region on r_regionkey = n_regionkey group by 1")
def join_universal(spark, d):
    """A summary of the joined relation itself."""
    j = table(spark, d, "supplier").join(table(spark, d, "nation"), F.expr("s_nationkey = n_nationkey")).join(table(spark, d, "region"), F.expr("r_regionkey = n_regionkey"))
    s = summarise(j, [Attr("n_name"), Attr("r_name")], [("n_name", "r_name")], per_pair=1000, rects="heavy", max_sweeps=100)
    return s.groups(["r_name"]).select("r_name", F.round("est", 3).alias("est"))


# -- baselines, hitters and measures ------------------------------------------------------------------

_KEYS = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
_UNIFORM = f"(select *, 100.0 as weight from {_C} where {samples.key_mix(_KEYS)} < 10000)"


@query(f"select l_orderkey, l_linenumber, l_partkey, l_suppkey, weight::double as weight from {_UNIFORM}")
def sample_uniform(spark, d):
    return samples.uniform_sample(wl.shop_coarse(spark, d, keys=True), 0.01, _KEYS).select(*_KEYS, "weight")


_CAP = """(select max(c) as cap from (select r.range + 1 as c from range(5000) r where (select sum(least(n, r.range + 1)) from h) <= (select floor(sum(n) * 0.01) from h) union all select 1))"""


@query(f"""with c as (select * from {_C}), h as (select p_brand, p_type, count(*) as n from c group by all),
r as (select c.*, n, row_number() over (partition by c.p_brand, c.p_type order by {samples.key_mix(_KEYS)}, l_orderkey, l_linenumber, l_partkey, l_suppkey) as rn from c join h on c.p_brand = h.p_brand and c.p_type = h.p_type)
select p_brand, p_type, count(*) as kept, round(max(greatest(1, n / cap)), 9) as weight from r, {_CAP} k where rn <= cap group by all""")
def sample_stratified(spark, d):
    s = samples.stratified_sample(wl.shop_coarse(spark, d, keys=True), ["p_brand", "p_type"], 0.01, _KEYS)
    return s.groupBy("p_brand", "p_type").agg(F.count(F.lit(1)).alias("kept"), F.round(F.max("weight"), 9).alias("weight"))


@query(f"select p_brand, sum(weight)::double as est from {_UNIFORM} group by 1")
def sample_estimate(spark, d):
    return samples.sample_groups(samples.uniform_sample(wl.shop_coarse(spark, d, keys=True), 0.01, _KEYS), ["p_brand"])


_PS = "(select p_size - 1 as p_size, gross, count(*) as n from " + _C + " group by 1, 2)"
for _kind, _sql in (
    ("heavy", f"select p_size, gross, n from {_PS} order by n desc, p_size, gross limit 100"),
    ("light", f"select p_size, gross, n from {_PS} order by n, p_size, gross limit 100"),
    ("absent", f"select a.range::int as p_size, b.range::int as gross, 0::bigint as n from range(50) a, range(81) b where (a.range, b.range) not in (select (p_size, gross) from {_PS}) order by (a.range * 7919 + b.range * 104729 + 0) % 1000003, 1, 2 limit 200"),
):

    def _hit(spark, d, kind=_kind):
        codes = wl.shop_coarse(spark, d).select((F.col("p_size") - 1).alias("p_size"), "gross")
        return wl.hitters(codes, ["p_size", "gross"], {"p_size": 50, "gross": 81}).where(F.col("kind") == kind).drop("kind")

    query(_sql, f"hitters_{_kind}")(_hit)


_SCORED = f"""(select 'heavy' as kind, h.n as truth, coalesce(u.est, 0)::double as est from (select p_size, gross, n from {_PS} order by n desc, p_size, gross limit 100) h left join (select p_size - 1 as p_size, gross, sum(weight) as est from {_UNIFORM} group by 1, 2) u using (p_size, gross)
union all select 'light', h.n, coalesce(u.est, 0) from (select p_size, gross, n from {_PS} order by n, p_size, gross limit 100) h left join (select p_size - 1 as p_size, gross, sum(weight) as est from {_UNIFORM} group by 1, 2) u using (p_size, gross)
union all select 'absent', 0, coalesce(u.est, 0) from (select a.range::int as p_size, b.range::int as gross from range(50) a, range(81) b where (a.range, b.range) not in (select (p_size, gross) from {_PS}) order by (a.range * 7919 + b.range * 104729) % 1000003, 1, 2 limit 200) h left join (select p_size - 1 as p_size, gross, sum(weight) as est from {_UNIFORM} group by 1, 2) u using (p_size, gross))"""


def _scored(spark, d):
    rel = wl.shop_coarse(spark, d, keys=True).withColumn("p_size", F.col("p_size") - 1)
    found = wl.hitters(rel.select("p_size", "gross"), ["p_size", "gross"], {"p_size": 50, "gross": 81})
    est = samples.sample_groups(samples.uniform_sample(rel, 0.01, _KEYS), ["p_size", "gross"])
    return found.join(est, ["p_size", "gross"], "left").select(
        F.lit("uniform").alias("method"), F.lit("p_size,gross").alias("template"), "kind", F.col("n").alias("truth"), F.coalesce("est", F.lit(0.0)).alias("est")
    )


@query(f"select kind, round(avg(case when truth + est = 0 then 0 else abs(truth - est) / (truth + est) end), 9) as error from {_SCORED} group by 1")
def metric_symmetric_error(spark, d):
    return metrics.mean_errors(_scored(spark, d)).select("kind", F.round("error", 9).alias("error"))


@query(f"""with k as (select count(*) filter (floor(est + 0.5) > 0 and kind = 'light') as hit, count(*) filter (floor(est + 0.5) > 0 and kind <> 'heavy') as said, count(*) filter (kind = 'light') as there from {_SCORED}),
p as (select coalesce(hit / nullif(said, 0), 0) as p, coalesce(hit / nullif(there, 0), 0) as r from k) select round(p, 9) as precision, round(r, 9) as recall, round(case when p + r = 0 then 0 else 2 * p * r / (p + r) end, 9) as f from p""")
def metric_fmeasure(spark, d):
    r = lambda c: F.round(c, 9).alias(c)
    return metrics.f_measures(_scored(spark, d)).select(r("precision"), r("recall"), r("f"))


@query(f"select round(sum(n) / {_T}, 9) as share from (select n from (select net, gross, count(*) as n from {_C} group by 1, 2) order by n desc, net, gross limit 100)")
def metric_heavy_share(spark, d):
    return metrics.heavy_share(wl.shop_coarse(spark, d), ["net", "gross"]).select(F.round("share", 9).alias("share"))


_TRIPLES = (("l_discount", "l_tax", "l_returnflag"), ("l_tax", "l_returnflag", "l_linestatus"), ("l_discount", "l_linenumber", "l_linestatus"))
_TRIPLE_SQL = " union all ".join(
    f"select '{a},{b},{c}' as attrs, count(distinct {a}) + count(distinct {b}) + count(distinct {c}) as w, count(distinct ({a}, {b})) as r, count(distinct ({b}, {c})) as q, count(distinct ({a}, {b}, {c})) as t from lineitem"
    for a, b, c in _TRIPLES
)


@query(f"""with m as ({_TRIPLE_SQL}), g as (select attrs, s.range::int as sets, r::int as rects, w * w::double as w2, t::double / (r * q) as kept from m, range(2, 5) s),
c as (select *, w2 * (case sets when 2 then pow(rects, 2) when 3 then 3 * pow(rects, 2) + 2 * pow(rects, 3) else 6 * pow(rects, 2) + 8 * pow(rects, 3) + 3 * pow(rects, 4) end) as a,
w2 * (sets * (sets - 1) / 2 * pow(rects, 2) + (sets - 1) * pow(rects * kept, sets)) as b from g) select attrs, sets, rects, round(kept, 9) as kept, sign(a - b)::int as sign from c""")
def build_cost_grid(spark, d):
    """Costs of both ways for the cells of two pairs that share an attribute, by the share of their combinations that hold rows."""
    cells = table(spark, d, "lineitem").groupBy(*sorted({a for t in _TRIPLES for a in t})).count().drop("count").collect()  # a row a cell
    rows = []
    for t in _TRIPLES:
        held = {tuple(r[a] for a in t) for r in cells if all(r[a] is not None for a in t)}
        first, last = {x[:2] for x in held}, {x[1:] for x in held}
        kept = len(held) / (len(first) * len(last))
        width = sum(len({x[i] for x in held}) for i in range(3))
        for sets in (2, 3, 4):
            sign = int(np.sign(costs.build_cost(width, sets, len(first), kept)["difference"]))
            rows.append((",".join(t), sets, len(first), round(kept, 9), sign))
    return spark.createDataFrame(rows, "attrs string, sets int, rects int, kept double, sign int")


# -- stored summaries and SQL access --------------------------------------------------------------


@query(f"select p_type, count(*) as n from {_C} group by 1")
def sink_summary(spark, d):
    s = _fitted(spark, d)
    path = scratch(spark, "summary")
    s.save(path)
    return Summary.load(spark, path).groups(["p_type"]).select("p_type", F.col("est_rounded").alias("n"))


@query()
def scan_summary(spark, d):
    """Groups of a summary through the data source; the filters become masks."""
    s = _fitted(spark, d, sweeps=30)
    spark.dataSource.register(SummarySource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    return spark.read.format("maxent_summary").option("by", "net,gross").option("model", model_option(s.model)).load().where("net >= 30 and gross <= 50")


@query(f"select round(count(*) * 1.0, 0)::bigint as n from {_C} where net >= 10")
def udtf_estimate(spark, d):
    register_udtf(spark, {"coarse": _fitted(spark, d)})
    return spark.sql("select est_rounded as n from maxent_estimate('coarse', 'net >= 10')")
