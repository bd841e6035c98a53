"""Accuracy and cost measures over (template, kind, truth, est) rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def symmetric_error(truth: Column | str, est: Column | str) -> Column:
    """|t - e| / (t + e), 0 where both are 0."""
    t = F.col(truth) if isinstance(truth, str) else truth
    e = F.col(est) if isinstance(est, str) else est
    return F.when(t + e == 0, F.lit(0.0)).otherwise(F.abs(t - e) / (t + e))


def mean_errors(rows: DataFrame) -> DataFrame:
    """(method, template, kind, error): mean symmetric error per method, template and kind of hitter."""
    return rows.groupBy("method", "template", "kind").agg(F.avg(symmetric_error("truth", "est")).alias("error"))


def error_difference(errors: DataFrame, reference: str) -> DataFrame:
    """Errors less those of a reference method on the same template and kind."""
    ref = errors.where(F.col("method") == reference).select("template", "kind", F.col("error").alias("ref"))
    return errors.join(ref, ["template", "kind"]).select("method", "template", "kind", (F.col("error") - F.col("ref")).alias("difference"))


def f_measures(rows: DataFrame) -> DataFrame:
    """(method, template, precision, recall, f): telling light groups from absent ones, an estimate counting after rounding."""
    found = F.floor(F.col("est") + 0.5) > 0
    per = rows.where("kind in ('light', 'absent')").groupBy("method", "template").agg(
        F.count_if(found & (F.col("kind") == "light")).alias("hit"),
        F.count_if(found).alias("said"),
        F.count_if(F.col("kind") == "light").alias("there"),
    )
    p, r = F.try_divide("hit", "said"), F.try_divide("hit", "there")
    scored = per.select("method", "template", F.coalesce(p, F.lit(0.0)).alias("precision"), F.coalesce(r, F.lit(0.0)).alias("recall"))
    pr = F.col("precision") + F.col("recall")
    return scored.withColumn("f", F.when(pr == 0, 0.0).otherwise(2 * F.col("precision") * F.col("recall") / pr))


def mean_f(per_template: DataFrame) -> DataFrame:
    return per_template.groupBy("method").agg(F.avg("f").alias("f"))


def heavy_share(codes: DataFrame, attrs: list[str], k: int = 100) -> DataFrame:
    """(share): part of all rows that the k largest groups hold."""
    counts = codes.groupBy(*attrs).agg(F.count(F.lit(1)).alias("n"))
    top = counts.orderBy(F.desc("n"), *attrs).limit(k).agg(F.sum("n").alias("t"))
    return counts.agg(F.sum("n").alias("all")).join(F.broadcast(top), F.lit(True)).select((F.col("t") / F.col("all")).alias("share"))
