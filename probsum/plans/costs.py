"""Operation counts of the two ways to build compatible groups."""

from __future__ import annotations

from math import comb

from pyspark.sql import DataFrame, SparkSession


def build_cost(width: float, sets: int, rects: float, kept: float) -> dict[str, float]:
    """Counts for `sets` attribute sets of `rects` rectangles, masks of `width` = attributes x values, share `kept` after pruning.

    per_subset joins every subset; outer_once prunes pairwise, joins once what is kept, then selects sub-groups.
    """
    plain = sum(comb(sets, k) * (k - 1) * width**2 * rects**k for k in range(2, sets + 1))
    pruned = rects * kept
    pre = comb(sets, 2) * (width * rects) ** 2
    once = pre + (sets - 1) * width**2 * pruned**sets
    return {"per_subset": plain, "outer_once": once, "difference": plain - once}


def build_cost_grid(spark: SparkSession, width: int = 5000, sets=(2, 3, 4), rects=(100, 500, 1000, 2000), kept=(0.1, 0.5, 1.0)) -> DataFrame:
    """(sets, rects, kept, per_subset, outer_once, difference, sign) over a parameter grid."""
    rows = [
        (s, r, float(p), *map(float, build_cost(width, s, r, p).values())) for s in sets for r in rects for p in kept
    ]
    frame = spark.createDataFrame(rows, "sets int, rects int, kept double, per_subset double, outer_once double, difference double")
    return frame.selectExpr("*", "cast(sign(difference) as int) as sign")
