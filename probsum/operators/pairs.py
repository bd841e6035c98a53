"""Which attribute pairs deserve two-dimensional statistics."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations
from math import comb

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def pair_scores(contingency: DataFrame, n: int, sizes: dict[str, int] | None = None) -> DataFrame:
    """(a, b, chi2, df, chi2_per_df, cramers_v, mi) of every pair.

    chi2 = n * (sum n_xy^2 / (n_x n_y) - 1), which accounts for empty cells exactly. Degrees of freedom
    count non-empty rows and columns, or the given domain sizes.
    """
    cells = contingency.withColumn("nx", F.sum("n").over(W.partitionBy("a", "b", "x"))).withColumn("ny", F.sum("n").over(W.partitionBy("a", "b", "y")))
    prod = F.col("nx").cast("double") * F.col("ny")
    sums = cells.groupBy("a", "b").agg(
        F.sum(F.col("n").cast("double") * F.col("n") / prod).alias("s"),
        F.sum(F.col("n") / F.lit(n) * F.ln(F.col("n").cast("double") * n / prod)).alias("mi"),
        F.size(F.collect_set("x")).alias("r"), F.size(F.collect_set("y")).alias("c"),
    )
    if sizes:
        size = F.create_map(*[v for k, s in sizes.items() for v in (F.lit(k), F.lit(s))])
        sums = sums.withColumn("r", size[F.col("a")]).withColumn("c", size[F.col("b")])
    chi2 = F.lit(float(n)) * (F.col("s") - 1)
    df = (F.col("r") - 1) * (F.col("c") - 1)
    return sums.select(
        "a", "b", chi2.alias("chi2"), df.cast("long").alias("df"),
        F.try_divide(chi2, df.cast("double")).alias("chi2_per_df"),
        F.sqrt(F.try_divide(F.greatest(chi2, F.lit(0.0)), n * F.least(F.col("r") - 1, F.col("c") - 1).cast("double"))).alias("cramers_v"),
        "mi",
    )


def pick_pairs(
    scores, count: int, policy: str = "cover", exclude=(), score: str = "chi2", most_subsets: int = 1_000_000
) -> list[tuple[str, str]]:
    """Choose `count` pairs from (a, b, score) rows; there are m^2 / 2 of them, m the attributes.

    correlation: by falling score, each pick bringing an attribute not seen before.
    cover: the set that covers most attributes, then has the largest total score, then comes first by name;
    exhaustive up to `most_subsets` sets, greedy beyond.
    mi_tree: edges of the maximum spanning forest on mutual information.
    """
    if isinstance(scores, DataFrame):
        scores = [(r["a"], r["b"], r["mi"] if policy == "mi_tree" else r[score]) for r in scores.collect()]
    rows = sorted(
        ((a, b, s) for a, b, s in scores if a not in exclude and b not in exclude), key=lambda r: (-r[2], r[0], r[1])
    )
    if policy == "correlation":
        out: list[tuple[str, str]] = []
        seen: set[str] = set()
        for a, b, _ in rows:
            if len(out) < count and not {a, b} <= seen:
                out.append((a, b))
                seen |= {a, b}
        return out
    if policy == "mi_tree":
        out, part = [], {}

        def root(x):
            while part.get(x, x) != x:
                x = part[x]
            return x

        for a, b, _ in rows:
            if len(out) < count and root(a) != root(b):
                part[root(a)] = root(b)
                out.append((a, b))
        return out
    if policy != "cover":
        raise ValueError(policy)
    count = min(count, len(rows))

    def value(pick):
        return len({x for a, b, _ in pick for x in (a, b)}), sum(s for *_, s in pick)

    if comb(len(rows), count) <= most_subsets:
        best = None
        for pick in combinations(rows, count):
            v = value(pick)
            names = sorted((a, b) for a, b, _ in pick)
            if best is None or v > best[0] or v == best[0] and names < best[1]:
                best = v, names, pick
        return [(a, b) for a, b, _ in best[2]] if best else []
    chosen: list = []
    while len(chosen) < count:
        chosen.append(max((r for r in rows if r not in chosen), key=lambda r: value([*chosen, r])))
    return [(a, b) for a, b, _ in chosen]


@dataclass(frozen=True)
class Budget:
    """A total number of two-dimensional statistics, shared equally by the pairs."""

    total: int
    pairs: int

    @property
    def per_pair(self) -> int:
        return self.total // self.pairs if self.pairs else 0
