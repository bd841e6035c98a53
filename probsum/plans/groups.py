"""Compatible groups of rectangles as DataFrames, for families too large for the driver.

rects: (stat_id, set_id, masks map<attr, array<long>>): masks holds one bit per value, 64 to a word. A group is
compatible if the words of every shared attribute still intersect after all of its members are taken; pairwise
overlap does not suffice for sets of values.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from probsum.plans.model import Family

SCHEMA = "stat_id int, set_id int, masks map<string, array<bigint>>"


def words(mask: np.ndarray) -> list[int]:
    """A bool vector as signed 64-bit words."""
    bits = np.pad(mask.astype(np.uint8), (0, -len(mask) % 64))
    return np.packbits(bits, bitorder="little").view(np.int64).tolist()


def rect_frame(spark: SparkSession, families: list[Family]) -> DataFrame:
    rows, sid = [], 0
    for s, fam in enumerate(families):
        for r in range(fam.size):
            rows.append((sid, s, {a: words(fam.masks[a][r]) for a in fam.attrs}))
            sid += 1
    return spark.createDataFrame(rows, SCHEMA)


def _meet(a: Column, b: Column) -> Column:
    """Masks of both: shared attributes intersected, the others kept."""
    return F.map_zip_with(
        a, b, lambda k, x, y: F.when(x.isNull(), y).when(y.isNull(), x).otherwise(F.zip_with(x, y, lambda p, q: p.bitwiseAND(q)))
    )


def _alive(masks: Column) -> Column:
    return F.forall(F.map_values(masks), lambda m: F.exists(m, lambda w: w != 0))


def compatible(a: Column, b: Column) -> Column:
    """Whether two mask maps intersect in every attribute they share."""
    return _alive(_meet(a, b))


def prune_isolated(rects: DataFrame) -> DataFrame:
    """Rectangles that meet a rectangle of another set, or share no attribute with one: a semi-join reduction."""
    a, b = rects.alias("a"), rects.select(*[F.col(c).alias(f"o_{c}") for c in rects.columns])
    return a.join(b, F.expr("set_id <> o_set_id") & compatible(F.col("masks"), F.col("o_masks")), "left_semi")


def _start(rects: DataFrame, s: int) -> DataFrame:
    return rects.where(F.col("set_id") == s).select(F.array("stat_id").alias("members"), "masks")


def _extend(groups: DataFrame, rects: DataFrame, s: int) -> DataFrame:
    own = rects.where(F.col("set_id") == s).select("stat_id", F.col("masks").alias("m2"))
    both = groups.join(own, compatible(F.col("masks"), F.col("m2")))
    return both.select(
        F.array_append("members", F.col("stat_id")).alias("members"), _meet(F.col("masks"), F.col("m2")).alias("masks")
    )


def compatible_groups(rects: DataFrame, sets: list[int], mode: str = "levelwise") -> DataFrame:
    """(members, masks) of all groups of two or more compatible rectangles, one per set at most.

    levelwise: sets are folded in order, each group kept and extended; one join per set and no repeats.
    per_subset: a chain of joins for every subset of sets. outer_once: one outer chain over all sets after
    pruning, whose rows are the maximal choices; sub-groups are selected out of them and repeats dropped.
    """
    if mode == "levelwise":
        out = None
        for s in sets:
            new = _start(rects, s)
            out = new if out is None else out.union(_extend(out, rects, s)).union(new)
        return out.where(F.size("members") > 1)
    if mode == "per_subset":
        parts = []
        for k in range(2, len(sets) + 1):
            for some in combinations(sets, k):
                g = _start(rects, some[0])
                for s in some[1:]:
                    g = _extend(g, rects, s)
                parts.append(g)
        out = parts[0]
        for p in parts[1:]:
            out = out.union(p)
        return out
    if mode != "outer_once":
        raise ValueError(mode)
    kept = prune_isolated(rects)
    chain = None
    for s in sets:
        own = kept.where(F.col("set_id") == s).select("stat_id", F.col("masks").alias("m2"))
        if chain is None:
            chain = own.select(F.array("stat_id").alias("members"), F.col("m2").alias("masks"))
            continue
        j = chain.join(own, compatible(F.col("masks"), F.col("m2")), "full_outer")
        grown = j.select(
            F.when(F.col("members").isNull(), F.array("stat_id"))
            .when(F.col("stat_id").isNull(), F.col("members"))
            .otherwise(F.array_append("members", F.col("stat_id")))
            .alias("members"),
            F.when(F.col("members").isNull(), F.col("m2")).when(F.col("stat_id").isNull(), F.col("masks")).otherwise(
                _meet(F.col("masks"), F.col("m2"))
            ).alias("masks"),
        )
        # a rectangle may also meet only a part of a chain: those parts start chains of their own
        parts = _subsets(chain, rects).join(own, compatible(F.col("masks"), F.col("m2")))
        partial = parts.select(
            F.array_append("members", F.col("stat_id")).alias("members"), _meet(F.col("masks"), F.col("m2")).alias("masks")
        )
        chain = grown.union(partial).dropDuplicates(["members"])
    return _subsets(chain, rects).where(F.size("members") > 1)


def _subsets(groups: DataFrame, rects: DataFrame) -> DataFrame:
    """All non-empty sub-groups of the members, each once, with their masks."""
    picked = groups.select(
        "members", F.explode(F.expr("sequence(1, cast(pow(2, size(members)) as int) - 1)")).alias("bits")
    ).select(F.expr("filter(members, (x, i) -> (bits & shiftleft(1, i)) <> 0)").alias("members"))
    return _with_masks(picked.dropDuplicates(), rects)


def _with_masks(members: DataFrame, rects: DataFrame) -> DataFrame:
    one = members.select("members", F.explode("members").alias("stat_id")).join(rects, "stat_id")
    flat = one.select("members", F.explode(F.map_entries("masks")).alias("e"))
    bits = flat.select("members", F.col("e.key").alias("attr"), F.posexplode("e.value").alias("word", "bits"))
    met = bits.groupBy("members", "attr", "word").agg(F.bit_and("bits").alias("bits"))
    rows = met.groupBy("members", "attr").agg(
        F.transform(F.array_sort(F.collect_list(F.struct("word", "bits"))), lambda w: w["bits"]).alias("m")
    )
    return rows.groupBy("members").agg(F.map_from_entries(F.collect_list(F.struct("attr", "m"))).alias("masks"))
