"""Sampling baselines: uniform and stratified samples with weights, and their estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from probsum.sources.tables import stored

MODULUS = 1_000_003
PARTS = 128  # parts of the key hashes that stratified_sample counts


def key_mix(keys: list[str]) -> str:
    """An integer hash of key columns that Spark and DuckDB compute alike."""
    primes = (7919, 104729, 1299709, 15485863)
    return "(" + " + ".join(f"{k} * {p}" for k, p in zip(keys, primes)) + f") % {MODULUS}"


def uniform_sample(df: DataFrame, rate: float, keys: list[str]) -> DataFrame:
    """Rows whose key hash falls under the rate, with weight 1 / rate; one scan, the same rows every time."""
    return df.where(F.expr(key_mix(keys)) < int(rate * MODULUS)).withColumn("weight", F.lit(1.0 / rate))


def bernoulli_sample(df: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    return df.sample(rate, seed).withColumn("weight", F.lit(1.0 / rate))


def stratum_cap(sizes: list[int], total: int) -> int:
    """Largest equal cap per stratum whose kept rows do not exceed `total`; at least 1."""
    lo, hi = 1, max(sizes, default=1)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if sum(min(s, mid) for s in sizes) <= total:
            lo = mid
        else:
            hi = mid - 1
    return lo


def cap_of(counts: DataFrame, total: int | None = None, rate: float = 1.0) -> int:
    """stratum_cap() from a (.., n) frame of strata, through the distribution of their sizes; `total` is `rate` of all rows if not given."""
    rows = counts.groupBy("n").agg(F.count(F.lit(1)).alias("m")).collect()  # distinct sizes, few beside the strata
    sizes = [(r["n"], r["m"]) for r in rows]
    total = int(sum(n * m for n, m in sizes) * rate) if total is None else total
    lo, hi = 1, max((n for n, _ in sizes), default=1)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if sum(min(n, mid) * m for n, m in sizes) <= total:
            lo = mid
        else:
            hi = mid - 1
    return lo


def stratified_sample(df: DataFrame, strata: list[str], rate: float, keys: list[str], exact: bool = True) -> DataFrame:
    """An equal cap of rows per stratum, as many in all as the uniform sample has, with weight n_h / k_h.

    exact: the first rows of a stratum by key hash; rows are counted by stratum and part of the hashes first, and only those up to the part
    that reaches the cap are sorted. Otherwise a row stays if its hash
    falls under cap / n_h: no sort and no hot stratum in one task, sizes being met on average; that is the form
    for large data.
    """
    h = F.expr(key_mix(keys))
    if not exact:
        counts = df.groupBy(*strata).agg(F.count(F.lit(1)).alias("n_h"))
        cap = cap_of(counts.withColumnRenamed("n_h", "n"), int(df.count() * rate))
        joined = df.join(counts, strata)
        kept = joined.where(h < F.least(F.lit(1.0), F.lit(cap) / F.col("n_h")) * MODULUS)
    else:
        part = F.floor(h * F.lit(PARTS) / F.lit(MODULUS))
        found = df.groupBy(*strata, part.alias("_p")).agg(F.count(F.lit(1)).alias("n_p"))
        by = W.partitionBy(*strata)
        upto = F.sum("n_p").over(by.orderBy("_p").rowsBetween(W.unboundedPreceding, W.currentRow))
        parts = stored(found.withColumn("n_h", F.sum("n_p").over(by)).withColumn("_upto", upto), "strata")
        cap = cap_of(parts.groupBy(*strata).agg(F.first("n_h").alias("n")), rate=rate)
        # the part in which the stratum's cap is reached: the rows to keep lie there or before
        last = F.coalesce(F.min(F.when(F.col("_upto") >= cap, F.col("_p"))), F.max("_p"))
        counts = parts.groupBy(*strata).agg(F.first("n_h").alias("n_h"), last.alias("_last"))
        few = df.join(counts, strata).where(part <= F.col("_last")).drop("_last")
        kept = few.withColumn("_r", F.row_number().over(by.orderBy(h, *keys))).where(F.col("_r") <= cap).drop("_r")
    return kept.withColumn("weight", F.greatest(F.lit(1.0), F.col("n_h") / F.lit(float(cap)))).drop("n_h")


def sample_groups(sample: DataFrame, by: list[str], where: str = "true") -> DataFrame:
    """(by.., est): weighted group counts of a sample."""
    return sample.where(where).groupBy(*by).agg(F.sum("weight").alias("est"))


def sample_count(sample: DataFrame, where: str = "true") -> float:
    return float(sample.where(where).agg(F.coalesce(F.sum("weight"), F.lit(0.0))).first()[0])


def exact_groups(codes: DataFrame, by: list[str], where: str = "true") -> DataFrame:
    return codes.where(where).groupBy(*by).agg(F.count(F.lit(1)).alias("n"))


def exact_count(codes: DataFrame, where: str = "true") -> int:
    return codes.where(where).count()
