"""Relational operators around the summaries: sources, joins, aggregates, windows, sets, scalars, UDFs."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from probsum.functions.domain import equi_width
from probsum.queries import query
from probsum.sources import workloads as wl
from probsum.sources.tables import partitioned, round_trip, table


# -- sources and sinks ----------------------------------------------------------


@query("select l_orderkey, l_quantity from lineitem where l_quantity >= 45")
def scan_parquet(spark, d):
    return table(spark, d, "lineitem").where("l_quantity >= 45").select("l_orderkey", "l_quantity")


for _fmt in ("csv", "json", "orc", "text"):

    def _scan(spark, d, fmt=_fmt):
        return round_trip(table(spark, d, "nation"), fmt, f"nation-{fmt}")

    query("select n_nationkey, n_name, n_regionkey from nation", f"scan_{_fmt}")(_scan)


@query("select * from (values ('a1','b1'),('a1','b1'),('a1','b2'),('a2','b2'),('a2','b2')) t(a, b)")
def scan_inline(spark, d):
    return spark.createDataFrame([("a1", "b1"), ("a1", "b1"), ("a1", "b2"), ("a2", "b2"), ("a2", "b2")], "a string, b string")


@query(f"select density, count(*) as n from {wl.PARTICLES_SQL} where snap = 1 group by 1")
def sink_partitioned(spark, d):
    path = partitioned(wl.particles_like(spark, d), "snap", "particles")
    return spark.read.parquet(path).where("snap = 1").groupBy("density").agg(F.count(F.lit(1)).alias("n"))


# -- projections and filters ------------------------------------------------------


@query("select l_orderkey, l_linenumber, greatest(least(floor(l_extendedprice / 1300), 80), 0)::int as gross from lineitem")
def project_bucket(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", equi_width("l_extendedprice", 1300, 0, 81).alias("gross"))


@query("""select p_partkey, case when p_size <= 10 then 'small' when p_size <= 30 then 'medium' else 'large' end as class,
coalesce(nullif(p_type, 'none'), 'x') as kind, p_size::double as size from part""")
def project_case(spark, d):
    size = F.col("p_size")
    return table(spark, d, "part").select(
        "p_partkey", F.when(size <= 10, "small").when(size <= 30, "medium").otherwise("large").alias("class"),
        F.coalesce(F.nullif("p_type", F.lit("none")), F.lit("x")).alias("kind"), size.cast("double").alias("size"),
    )


def _filtered(name: str, spark_where: str, sql_where: str | None = None):
    def f(spark, d):
        return wl.shop_coarse(spark, d).where(spark_where).groupBy("p_brand", "p_size").agg(F.count(F.lit(1)).alias("n"))

    query(f"select p_brand, p_size, count(*) as n from {wl.COARSE_SQL} where {sql_where or spark_where} group by 1, 2", name)(f)


_filtered("filter_point", "p_size = 7 and gross = 3")
_filtered("filter_range", "gross between 20 and 40")
_filtered("filter_in", "p_size in (1, 5, 9) and ship_month in (3, 14)")
_filtered("filter_like", "p_brand like '%1_'")
_filtered("filter_disjunction", "p_size = 3 or gross >= 70")


@query("select d.doc_id, lang from documents d left join labels l on d.doc_id = l.doc_id where quality is null")
def filter_null(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left").where(F.col("quality").isNull()).select("doc_id", "lang")


# -- joins ------------------------------------------------------------------------


@query("select p_brand, count(*) as n, round(sum(l_quantity), 2) as qty from lineitem join part on l_partkey = p_partkey group by 1")
def join_broadcast(spark, d):
    part = table(spark, d, "part").select("p_partkey", "p_brand")
    j = table(spark, d, "lineitem").join(part.hint("broadcast") if part.count() <= 1_000_000 else part, F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


def _orders_join(hint):
    def f(spark, d):
        o = table(spark, d, "orders").select("o_orderkey", "o_orderpriority").hint(hint)
        j = table(spark, d, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
        return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))

    return f


_orders_sql = "select o_orderpriority, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by 1"
query(_orders_sql, "join_sortmerge")(_orders_join("merge"))
query(_orders_sql, "join_shuffle_hash")(_orders_join("shuffle_hash"))

_RECTS = """select o_custkey * 10000 + year(o_orderdate) as id, min(month(o_orderdate)) as x0, max(month(o_orderdate)) as x1, min(floor(o_totalprice / 1000)::int) as y0, max(floor(o_totalprice / 1000)::int) as y1
from orders where o_custkey <= 40 group by o_custkey, year(o_orderdate)"""


@query(f"""select a.id as left_id, b.id as right_id from ({_RECTS}) a join (select id, x0 + 5 as x0, x1 + 5 as x1, y0, y1 from ({_RECTS})) b
on a.x0 <= b.x1 and b.x0 <= a.x1 and a.y0 <= b.y1 and b.y0 <= a.y1""")
def join_theta(spark, d):
    """Months and prices that forty customers' orders of a year span, against the same five months later."""
    month, price = F.month("o_orderdate"), F.floor(F.col("o_totalprice") / 1000).cast("int")
    rects = table(spark, d, "orders").where("o_custkey <= 40").groupBy((F.col("o_custkey") * 10000 + F.year("o_orderdate")).alias("id")).agg(
        F.min(month).alias("x0"), F.max(month).alias("x1"), F.min(price).alias("y0"), F.max(price).alias("y1")
    )
    b = rects.selectExpr("id as id2", "x0 + 5 as u0", "x1 + 5 as u1", "y0 as v0", "y1 as v1")
    return rects.join(b, F.expr("x0 <= u1 and u0 <= x1 and y0 <= v1 and v0 <= y1")).selectExpr("id as left_id", "id2 as right_id")


@query("""select b as bucket, count(*) as n from lineitem join (select b, b * 13000.0 as lo, (b + 1) * 13000.0 as hi from range(10) r(b)) on l_extendedprice >= lo and l_extendedprice < hi group by 1""")
def join_range(spark, d):
    """Range join as an equi-join on a coarse bucket, then the exact bounds."""
    edges = spark.range(10).selectExpr("id as b", "id * 13000D as lo", "(id + 1) * 13000D as hi")
    keyed = edges.select("*", F.explode(F.sequence(F.floor(F.col("lo") / 5000), F.floor(F.col("hi") / 5000))).alias("k"))
    line = table(spark, d, "lineitem").select("l_extendedprice", F.floor(F.col("l_extendedprice") / 5000).alias("k"))
    return line.join(keyed, "k").where("l_extendedprice >= lo and l_extendedprice < hi").groupBy(F.col("b").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@query("""select e.event_id, max(p.event_id) as prev_id from events e left join events p
on p.user_id = e.user_id and p.event_type = 'purchase' and e.event_type <> 'purchase' and p.ts < e.ts
and p.ts = (select max(q.ts) from events q where q.user_id = e.user_id and q.event_type = 'purchase' and q.ts < e.ts)
where e.event_type <> 'purchase' group by 1""")
def join_asof(spark, d):
    """Latest earlier purchase of the user, by one window over both sides."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    buys = e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("b"))
    both = e.where("event_type <> 'purchase'").selectExpr("user_id", "ts", "event_id", "cast(null as bigint) as b").unionByName(buys.selectExpr("user_id", "ts", "cast(null as bigint) as event_id", "b"))
    w = W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(W.unboundedPreceding, -1)
    return both.withColumn("prev_id", F.last("b", ignorenulls=True).over(w)).where("event_id is not null").select("event_id", "prev_id")


@query("select o_orderpriority, count(*) as n from orders join lineitem on o_orderkey = l_orderkey and l_shipdate >= o_orderdate and l_shipdate < o_orderdate + interval 30 day group by 1")
def join_interval(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_orderdate", "o_orderpriority")
    line = table(spark, d, "lineitem").select("l_orderkey", "l_shipdate")
    on = F.expr("o_orderkey = l_orderkey and l_shipdate >= o_orderdate and l_shipdate < o_orderdate + interval 30 days")
    return o.join(line, on).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


for _kind, _not in (("semi", ""), ("anti", "not ")):

    def _exists(spark, d, kind=_kind):
        line = table(spark, d, "lineitem").select("l_orderkey")
        return table(spark, d, "orders").join(line, F.col("o_orderkey") == F.col("l_orderkey"), f"left_{kind}").select("o_orderkey")

    query(f"select o_orderkey from orders where {_not}exists (select 1 from lineitem where l_orderkey = o_orderkey)", f"join_{_kind}")(_exists)

for _kind in ("left", "right", "full"):

    def _outer(spark, d, kind=_kind):
        docs, labels = table(spark, d, "documents").select("doc_id", "lang"), table(spark, d, "labels").where("toxic = 1").selectExpr("doc_id as label_id", "toxic")
        on = F.col("doc_id") == F.col("label_id")
        return docs.where("lang <> 'fr'").join(labels, on, kind).select("doc_id", "lang", "label_id", "toxic")

    query(f"select d.doc_id, lang, l.doc_id as label_id, toxic from (select * from documents where lang <> 'fr') d {_kind} join (select * from labels where toxic = 1) l on d.doc_id = l.doc_id", f"join_{_kind}")(_outer)


@query("select r_regionkey, x.range as k from region cross join range(12) x")
def join_cross(spark, d):
    return table(spark, d, "region").select("r_regionkey").crossJoin(spark.range(12).withColumnRenamed("id", "k"))


@query("select a.c_nationkey, count(*) as n from customer a join customer b on a.c_nationkey = b.c_nationkey and a.c_mktsegment = b.c_mktsegment and a.c_custkey < b.c_custkey group by 1")
def join_self(spark, d):
    """Pairs of customers alike, counted from group sizes: no pair is made."""
    g = table(spark, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("m"))
    return g.groupBy("c_nationkey").agg(F.sum(F.expr("m * (m - 1) div 2")).alias("n")).where("n > 0")


@query("select c_nationkey as nation, count(*) as n from customer join supplier on c_nationkey = s_nationkey group by 1")
def join_many_to_many(spark, d):
    """Join size per key from both sides' counts."""
    c = table(spark, d, "customer").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("a"))
    s = table(spark, d, "supplier").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("b"))
    return c.join(s, F.col("c_nationkey") == F.col("s_nationkey")).selectExpr("c_nationkey as nation", "a * b as n")


@query("select r_name, count(*) as n, round(sum(o_totalprice), 2) as total from region join nation on r_regionkey = n_regionkey join customer on c_nationkey = n_nationkey join orders on o_custkey = c_custkey group by 1")
def join_chain(spark, d):
    t = table(spark, d, "orders").join(table(spark, d, "customer"), F.expr("o_custkey = c_custkey"))
    t = t.join(table(spark, d, "nation"), F.expr("c_nationkey = n_nationkey")).join(table(spark, d, "region"), F.expr("n_regionkey = r_regionkey"))
    return t.groupBy("r_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


# -- aggregates -------------------------------------------------------------------


@query("select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(avg(l_extendedprice), 4) as price, count(*) as n from lineitem group by 1, 2")
def agg_hash(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.count(F.lit(1)).alias("n"),
    )


@query("select p_size, string_agg(p_partkey::varchar, ',' order by p_partkey) as parts from part where p_partkey <= 500 group by 1")
def agg_sort(spark, d):
    g = table(spark, d, "part").where("p_partkey <= 500").groupBy("p_size").agg(F.sort_array(F.collect_list("p_partkey")).alias("l"))
    return g.select("p_size", F.array_join(F.col("l").cast("array<string>"), ",").alias("parts"))


@query("select event_type, count(distinct user_id) as users, count(distinct date_trunc('day', ts)) as days from events group by 1")
def agg_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct(F.to_date("ts")).alias("days"))


@query()
def agg_approx_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@query(f"select p_brand, p_size, p_type, count(*) as n from {wl.COARSE_SQL} group by grouping sets ((p_brand, p_size), (p_size, p_type), (p_brand), ())")
def agg_grouping_sets(spark, d):
    c = ["p_brand", "p_size", "p_type"]
    return wl.shop_coarse(spark, d).groupingSets([["p_brand", "p_size"], ["p_size", "p_type"], ["p_brand"], []], *c).agg(F.count(F.lit(1)).alias("n")).select(*c, "n")


@query("select l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::bigint as g, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def agg_cube(spark, d):
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@query("select l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::bigint as g, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
def agg_rollup(spark, d):
    return table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@query("select l_returnflag, count(*) filter (l_quantity > 25) as big, round(coalesce(sum(l_tax) filter (l_discount = 0), 0), 6) as tax from lineitem group by 1")
def agg_filtered(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.count_if(F.col("l_quantity") > 25).alias("big"), F.round(F.sum(F.when(F.col("l_discount") == 0, F.col("l_tax")).otherwise(0.0)), 6).alias("tax")
    )


@query("select round(avg(net), 6) as mean, round(stddev_samp(net), 6) as sd, round(var_pop(gross), 6) as var, round(corr(net::double, gross::double), 6) as corr, round(covar_pop(net::double, gross::double), 4) as cov from " + wl.COARSE_SQL)
def agg_stats(spark, d):
    return wl.shop_coarse(spark, d).agg(
        F.round(F.avg("net"), 6).alias("mean"), F.round(F.stddev_samp("net"), 6).alias("sd"), F.round(F.var_pop("gross"), 6).alias("var"),
        F.round(F.corr("net", "gross"), 6).alias("corr"), F.round(F.covar_pop("net", "gross"), 4).alias("cov"),
    )


@query("select l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) as med, round(quantile_cont(l_extendedprice, 0.9), 4) as p90 from lineitem group by 1")
def agg_quantile(spark, d):
    p = lambda q: F.round(F.percentile("l_extendedprice", q), 4)
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(p(0.5).alias("med"), p(0.9).alias("p90"))


@query()
def agg_approx_quantile(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_percentile("l_extendedprice", 0.5, 1000).alias("med"))


@query("select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as best, arg_min(o_orderkey, (o_totalprice, o_orderkey)) as worst from orders group by 1")
def agg_argmax(spark, d):
    key = F.struct("o_totalprice", "o_orderkey")
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", key).alias("best"), F.min_by("o_orderkey", key).alias("worst"))


@query("select p_brand, string_agg(p_type, '|' order by p_type) as types from (select distinct p_brand, p_type from part) group by 1")
def agg_collect(spark, d):
    return table(spark, d, "part").groupBy("p_brand").agg(F.array_join(F.sort_array(F.collect_set("p_type")), "|").alias("types"))


@query("select turn, count(*) filter (role = 'user') as user, count(*) filter (role = 'assistant') as assistant, count(*) filter (role = 'system') as system from conversations group by 1")
def agg_pivot(spark, d):
    p = table(spark, d, "conversations").groupBy("turn").pivot("role", ["user", "assistant", "system"]).count()
    return p.na.fill(0, ["user", "assistant", "system"])


@query("select r_regionkey, 'key' as name, r_regionkey::varchar as value from region union all select r_regionkey, 'name', r_name from region")
def agg_unpivot(spark, d):
    return table(spark, d, "region").selectExpr("r_regionkey", "cast(r_regionkey as string) as key", "r_name as name").unpivot(["r_regionkey"], ["key", "name"], "name", "value")


@query(f"select p_brand, p_size, count(*) as n from {wl.COARSE_SQL} group by 1, 2 having count(*) > 60")
def agg_having(spark, d):
    return wl.shop_coarse(spark, d).groupBy("p_brand", "p_size").agg(F.count(F.lit(1)).alias("n")).where("n > 60")


# -- sketches -----------------------------------------------------------------------


@query()
def sk_countmin(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.length(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(42))).alias("bytes"))


@query()
def sk_hll(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 12)).alias("users"))


@query()
def sk_histogram(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.size(F.histogram_numeric("value", F.lit(10))).alias("bins"))


# -- windows --------------------------------------------------------------------------


@query("""select p_partkey, row_number() over w as rn, rank() over (partition by p_brand order by p_size) as rk, dense_rank() over (partition by p_brand order by p_size) as dr, ntile(4) over w as q
from part window w as (partition by p_brand order by p_size, p_partkey)""")
def win_rank(spark, d):
    w, s = W.partitionBy("p_brand").orderBy("p_size", "p_partkey"), W.partitionBy("p_brand").orderBy("p_size")
    return table(spark, d, "part").select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(s).alias("rk"), F.dense_rank().over(s).alias("dr"), F.ntile(4).over(w).alias("q"))


@query("select p_partkey, round(percent_rank() over w, 9) as pr, round(cume_dist() over w, 9) as cd from part window w as (partition by p_type order by p_retailprice)")
def win_dist(spark, d):
    w = W.partitionBy("p_type").orderBy("p_retailprice")
    return table(spark, d, "part").select("p_partkey", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("""select event_id, lag(event_id) over w as before, lead(event_id, 2) over w as after, first_value(event_id) over w as first,
last_value(event_id) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as last, nth_value(event_id, 2) over w as second
from events window w as (partition by user_id order by ts, event_id)""")
def win_shift(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, d, "events").select(
        "event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first("event_id").over(w).alias("first"),
        F.last("event_id").over(whole).alias("last"), F.nth_value("event_id", 2).over(w).alias("second"),
    )


@query("select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 6) as total from events")
def win_running(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return table(spark, d, "events").select("event_id", F.round(F.sum("value").over(w), 6).alias("total"))


_GRID_SQL = f"(select x, y, coalesce(n, 0) as n from (select a.range::int as x, b.range::int as y from range(50) a, range(6) b) left join (select p_size - 1 as x, code as y, count(*) as n from {wl.COARSE_SQL} join (select p_type as t, (row_number() over (order by p_type) - 1)::int as code from (select distinct p_type from part)) on p_type = t group by 1, 2) using (x, y))"


@query(f"select x, y, (sum(r) over (partition by y order by x))::bigint as s from (select x, y, sum(n) over (partition by x order by y) as r from {_GRID_SQL})")
def win_prefix2d(spark, d):
    """Prefix sums of a count matrix in two windows; the grid is a product of two domains."""
    types = table(spark, d, "part").select("p_type").distinct().withColumn("y", (F.row_number().over(W.orderBy("p_type")) - 1).cast("int"))
    cells = wl.shop_coarse(spark, d).join(types, "p_type").groupBy((F.col("p_size") - 1).alias("x"), "y").agg(F.count(F.lit(1)).alias("n"))
    grid = spark.range(50).selectExpr("cast(id as int) as x").crossJoin(spark.range(6).selectExpr("cast(id as int) as y"))
    full = grid.join(cells, ["x", "y"], "left").na.fill(0, ["n"])
    r = full.withColumn("r", F.sum("n").over(W.partitionBy("x").orderBy("y")))
    return r.select("x", "y", F.sum("r").over(W.partitionBy("y").orderBy("x")).alias("s"))


@query("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")
def win_range(spark, d):
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return table(spark, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


# -- order, limits, sets ------------------------------------------------------------------


@query("select o_orderkey, o_totalprice from orders")
def sort_total(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("select o_orderkey, o_custkey from orders")
def sort_within(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_custkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")
def limit_topk(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) <= 3")
def topk_per_group(spark, d):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


def _cells(spark, d, snap):
    return wl.particles_like(spark, d).where(f"snap = {snap}").select("density", "mass", "y")


_A, _B = (f"select density, mass, y from {wl.PARTICLES_SQL} where snap = {s}" for s in (0, 1))
for _name, _sql, _op in (
    ("set_union", f"{_A} union all {_B}", lambda a, b: a.union(b)),
    ("set_union_by_name", f"{_A} union all {_B}", lambda a, b: a.unionByName(b.select("y", "mass", "density"))),
    ("set_intersect", f"{_A} intersect {_B}", lambda a, b: a.intersect(b)),
    ("set_intersect_all", f"{_A} intersect all {_B}", lambda a, b: a.intersectAll(b)),
    ("set_except", f"{_A} except {_B}", lambda a, b: a.subtract(b)),
    ("set_except_all", f"{_A} except all {_B}", lambda a, b: a.exceptAll(b)),
    ("set_distinct", f"select distinct * from ({_A})", lambda a, b: a.distinct()),
):
    query(_sql, _name)(lambda spark, d, op=_op: op(_cells(spark, d, 0), _cells(spark, d, 1)))


# -- scalar functions ---------------------------------------------------------------------


@query("""select p_partkey, upper(p_name) as up, split_part(p_name, ' ', 1) as head, substr(p_name, 2, 3) as mid, length(p_name)::int as len, concat_ws('-', p_brand, p_type) as tag,
trim('  ' || p_type || ' ') as tidy, regexp_extract(p_brand, '([0-9]+)', 1) as digits, translate(p_name, 'aeiou', '12345') as coded, levenshtein(p_name, p_type)::int as dist from part""")
def fn_string(spark, d):
    n = F.col("p_name")
    return table(spark, d, "part").select(
        "p_partkey", F.upper(n).alias("up"), F.split(n, " ")[0].alias("head"), F.substring(n, 2, 3).alias("mid"), F.length(n).alias("len"),
        F.concat_ws("-", "p_brand", "p_type").alias("tag"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("tidy"),
        F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.translate(n, "aeiou", "12345").alias("coded"), F.levenshtein(n, "p_type").alias("dist"),
    )


@query("""select l_orderkey, l_partkey, l_suppkey, l_linenumber, year(l_shipdate)::int as y, month(l_shipdate)::int as m, strftime(date_trunc('month', l_shipdate), '%Y-%m-%d') as mon,
date_diff('day', date '1995-01-01', l_shipdate::date)::int as days, strftime(l_shipdate::date + interval 2 month, '%Y-%m-%d') as later, strftime(last_day(l_shipdate), '%Y-%m-%d') as last from lineitem""")
def fn_date(spark, d):
    s = F.to_date("l_shipdate")
    text = lambda c: F.date_format(c, "yyyy-MM-dd")
    return table(spark, d, "lineitem").select(
        "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.year(s).alias("y"), F.month(s).alias("m"), text(F.date_trunc("month", s)).alias("mon"),
        F.datediff(s, F.lit("1995-01-01")).alias("days"), text(F.add_months(s, 2)).alias("later"), text(F.last_day(s)).alias("last"),
    )


@query("""select l_orderkey, l_linenumber, floor(l_extendedprice / 7)::bigint as f, round(l_extendedprice, 1) as r, round(ln(l_extendedprice), 6) as ln, round(log2(l_extendedprice), 6) as l2, round(exp(l_discount), 9) as e,
round(ln(1 + l_tax), 9) as l1p, round(exp(l_tax) - 1, 9) as em1, ((l_orderkey % 7) + 7) % 7 as pm, greatest(l_quantity, 25) as g, least(l_quantity, 25) as l,
least(greatest(floor((l_extendedprice - 900) / 10000) + 1, 0), 11)::bigint as wb from lineitem""")
def fn_math(spark, d):
    p = F.col("l_extendedprice")
    return table(spark, d, "lineitem").select(
        "l_orderkey", "l_linenumber", F.floor(p / 7).alias("f"), F.round(p, 1).alias("r"), F.round(F.ln(p), 6).alias("ln"), F.round(F.log2(p), 6).alias("l2"),
        F.round(F.exp("l_discount"), 9).alias("e"), F.round(F.log1p("l_tax"), 9).alias("l1p"), F.round(F.expm1("l_tax"), 9).alias("em1"),
        F.pmod("l_orderkey", F.lit(7)).alias("pm"), F.greatest("l_quantity", F.lit(25.0)).alias("g"), F.least("l_quantity", F.lit(25.0)).alias("l"),
        F.width_bucket(p, F.lit(900.0), F.lit(100900.0), F.lit(10)).alias("wb"),
    )


@query("""select vec_id, round(embedding[1]::double, 6) as head, len(embedding)::int as n, len(list_filter(embedding, lambda x: x > 0))::int as pos,
round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) as norm, len(list_intersect([1, 2, vec_id % 4], [2, 3]))::int as common from embeddings""")
def fn_array(spark, d):
    return table(spark, d, "embeddings").selectExpr(
        "vec_id", "round(cast(embedding[0] as double), 6) as head", "size(embedding) as n", "size(filter(embedding, x -> x > 0)) as pos",
        "round(aggregate(zip_with(embedding, embedding, (x, y) -> cast(x as double) * cast(y as double)), 0D, (s, x) -> s + x), 6) as norm",
        "size(array_intersect(array(1L, 2L, vec_id % 4), array(2L, 3L))) as common",
    )


@query("select r_regionkey, r_regionkey * 10 as ten, (r_regionkey * 10 + 1)::int as ten_up, 1 as kept from region")
def fn_map(spark, d):
    r = table(spark, d, "region").withColumn("m", F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array(F.col("r_regionkey") * 10, F.lit(-1))))
    up = F.transform_values("m", lambda k, v: v + 1)
    return r.select("r_regionkey", F.element_at("m", "a").alias("ten"), F.element_at(up, "a").alias("ten_up"), F.size(F.map_filter("m", lambda k, v: v >= 0)).alias("kept"))


@query("""select event_id, (props->>'$.k')::int as k, ('{"k":' || (props->>'$.k') || '}') as again from events""")
def fn_json(spark, d):
    parsed = F.from_json("props", "k int")
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.to_json(parsed).alias("again"))


@query("select s_nationkey, bit_or(1::bigint << (s_suppkey % 60)::int)::bigint as mask, bit_count(bit_or(1::bigint << (s_suppkey % 60)::int))::int as bits, (bit_or(1::bigint << (s_suppkey % 60)::int) & 255)::bigint as low from supplier group by 1")
def fn_bits(spark, d):
    mask = F.expr("shiftleft(1L, cast(s_suppkey % 60 as int))")
    g = table(spark, d, "supplier").groupBy("s_nationkey").agg(F.bit_or(mask).alias("mask"))
    return g.select("s_nationkey", "mask", F.bit_count("mask").alias("bits"), F.col("mask").bitwiseAND(F.lit(255).cast("long")).alias("low"))


# -- user-defined functions --------------------------------------------------------------------


@query("select a.range::int as a, b.range::int as b from range(40) a, range(40) b where ((a.range * 37 + 5) & (b.range * 91 + 3)) <> 0")
def udf_overlap(spark, d):
    """Arrow scalar UDF on bitmaps: do two value sets intersect?"""

    def meet(x: pd.Series, y: pd.Series) -> pd.Series:
        return (x.to_numpy() & y.to_numpy()) != 0

    overlap = F.pandas_udf(lambda x, y: pd.Series(meet(x, y)), "boolean")
    a = spark.range(40).selectExpr("cast(id as int) as a", "id * 37 + 5 as ma")
    b = spark.range(40).selectExpr("cast(id as int) as b", "id * 91 + 3 as mb")
    return a.crossJoin(b).where(overlap("ma", "mb")).select("a", "b")


@query(f"select p_brand, round(sqrt(sum((n - m) * (n - m))), 6) as err from (select p_brand, p_size, count(*) as n, avg(count(*)) over (partition by p_brand) as m from {wl.COARSE_SQL} group by 1, 2) group by 1")
def udaf_leaf_error(spark, d):
    """Pandas grouped aggregate: root squared error of a leaf's cells about their mean."""

    @F.pandas_udf("double")
    def leaf_error(n: pd.Series) -> float:
        return float(np.sqrt(((n - n.mean()) ** 2).sum()))

    cells = wl.shop_coarse(spark, d).groupBy("p_brand", "p_size").agg(F.count(F.lit(1)).alias("n"))
    return cells.groupBy("p_brand").agg(leaf_error("n").alias("err")).select("p_brand", F.round("err", 6).alias("err"))


@query(f"select a, b, x, y, n from (select 'net' as a, 'gross' as b, net as x, gross as y, count(*) as n from {wl.COARSE_SQL} group by all union all select 'ship_month', 'ship_month', ship_month::int, 0, count(*) from {wl.COARSE_SQL} group by all)")
def udf_bincount(spark, d):
    """Dense counts per task, summed by slot: value and pair statistics without Expand."""
    from probsum.operators.stats import dense_counts

    codes = wl.shop_coarse(spark, d).select("ship_month", "net", "gross")
    return dense_counts(codes, {"ship_month": 83, "net": 62, "gross": 81}, [("net", "gross"), ("ship_month", "ship_month")])
