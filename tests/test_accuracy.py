"""The accuracy experiments count every relation once, and as group-bys do."""

import numpy as np
from pyspark.sql import functions as F

from probsum.functions.domain import encode
from probsum.operators import samples, stats
from probsum.plans import summary
from probsum.queries import experiments
from probsum.sources import workloads as wl


def test_templates_are_counted_as_by_group_by(spark, sf):
    codes, domain = encode(wl.shop_coarse(spark, sf), wl.coarse_attrs())
    sizes = summary.sizes_of(domain, wl.coarse_attrs())
    sets = [("p_brand", "p_size"), ("net", "gross"), ("p_brand", "p_size", "p_type")]
    got = stats.dense_groups(codes, sizes, sets)
    weighed = stats.dense_groups(codes.withColumn("weight", F.lit(2.5)), sizes, sets, "weight")
    for s in sets:
        want = np.zeros([sizes[a] for a in s])
        for r in samples.exact_groups(codes, list(s)).collect():
            want[tuple(r[a] for a in s)] = r["n"]
        assert (got[s] == want).all()
        assert np.allclose(weighed[s], 2.5 * want)
        rows = {(r["kind"], tuple(r[a] for a in s), r["n"]) for r in wl.hitters(codes, list(s), sizes, 20, 20, 30).collect()}
        assert set(wl.hitters_of(got[s], s, 20, 20, 30)) == rows


def test_one_pass_of_counts_for_all_summaries(spark, sf, monkeypatch):
    made = []
    real = summary.collect_counts

    def counted(*args, **options):
        made.append(real(*args, **options))
        return made[-1]

    monkeypatch.setattr(summary, "collect_counts", counted)
    monkeypatch.setattr(experiments, "collect_counts", counted)
    assert experiments.accuracy_fine(spark, sf).count() == 12
    assert len(made) == 1
    assert not made[0].cached.storageLevel.useMemory and not made[0].domain.storageLevel.useMemory  # nothing stays on the driver


def test_stratified_sample_sorts_only_the_first_parts(spark, sf, monkeypatch):
    """The rows kept are the first of every stratum by key hash; those that are ranked are few of all."""
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    rel, strata, rate = wl.shop_coarse(spark, sf, keys=True), ["net", "gross"], 0.02
    pdf = rel.toPandas()
    h = sum(pdf[k] * p for k, p in zip(keys, (7919, 104729, 1299709, 15485863))) % samples.MODULUS
    pdf = pdf.assign(h=h).sort_values(["h", *keys])
    sizes = pdf.groupby(strata).size()
    cap = samples.stratum_cap(sizes.tolist(), int(len(pdf) * rate))
    want = {tuple(r) for r in pdf.groupby(strata).head(cap)[keys].itertuples(index=False)}
    ranked = []
    real = samples.F.row_number
    monkeypatch.setattr(samples.F, "row_number", lambda: ranked.append(1) or real())
    got = samples.stratified_sample(rel, strata, rate, keys)
    assert {tuple(r[k] for k in keys) for r in got.collect()} == want
    assert ranked and "_last" in got._jdf.queryExecution().optimizedPlan().toString()


def test_groups_come_to_the_driver_as_arrays(spark, monkeypatch):
    """No row a group reaches the driver: toPandas() and collect() are not used on them."""
    from pyspark.sql.classic.dataframe import DataFrame

    codes = spark.range(60_000).select((F.col("id") % 300).cast("int").alias("x"), (F.col("id") % 500).cast("int").alias("y"), F.lit(0.5).alias("w"))
    want = {}
    for i in range(60_000):
        want[i % 300, i % 500] = want.get((i % 300, i % 500), 0) + 1

    def refused(*_):
        raise AssertionError("rows of groups on the driver")

    monkeypatch.setattr(DataFrame, "toPandas", refused)
    monkeypatch.setattr(DataFrame, "collect", refused)
    n = stats.dense_groups(codes, {"x": 300, "y": 500}, [("x", "y")])["x", "y"]
    w = stats.dense_groups(codes, {"x": 300, "y": 500}, [("x", "y")], "w")["x", "y"]
    assert n.sum() == 60_000 and all(n[p] == v and w[p] == v / 2 for p, v in want.items())
