"""Count statistics of a coded relation: the only passes over the data."""

from __future__ import annotations

import zlib
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def base_cuboid(codes: DataFrame) -> DataFrame:
    """Counts of the distinct code tuples: the sparse frequency vector."""
    return codes.groupBy(*codes.columns).agg(F.count(F.lit(1)).alias("n"))


def _counted(codes: DataFrame) -> DataFrame:
    return codes if "n" in codes.columns else codes.withColumn("n", F.lit(1).cast("long"))


def value_stats(codes: DataFrame) -> DataFrame:
    """(attr, code, n) of every attribute in one pass, by grouping sets."""
    names = [c for c in codes.columns if c != "n"]
    sets = _counted(codes).groupingSets([[c] for c in names], *names).agg(
        F.sum("n").alias("n"), F.grouping_id(*[F.col(c) for c in names]).alias("g")
    )
    m = len(names)
    which = F.element_at(
        F.create_map(*[x for i, c in enumerate(names) for x in (F.lit((1 << m) - 1 - (1 << (m - 1 - i))), F.lit(c))]),
        F.col("g").cast("int"),
    )
    return sets.select(which.alias("attr"), F.coalesce(*names).alias("code"), "n")


def contingencies(codes: DataFrame, pairs: list[tuple[str, str]] | None = None) -> DataFrame:
    """(a, b, x, y, n) of every pair of attributes in one pass, by grouping sets; empty cells are left out."""
    names = [c for c in codes.columns if c != "n"]
    pairs = pairs or list(combinations(names, 2))
    used = [c for c in names if any(c in p for p in pairs)]
    m = len(used)
    bit = {c: 1 << (m - 1 - i) for i, c in enumerate(used)}
    sets = _counted(codes).select(*used, "n").groupingSets([list(p) for p in pairs], *used).agg(
        F.sum("n").alias("n"), F.grouping_id(*[F.col(c) for c in used]).alias("g")
    )
    cell = F.element_at(
        F.create_map(
            *[
                v
                for a, b in pairs
                for v in (
                    F.lit((1 << m) - 1 - bit[a] - bit[b]),
                    F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")),
                )
            ]
        ),
        F.col("g").cast("int"),
    )
    def pick(side: str):
        out = F.when(F.col("p")[side] == used[0], F.col(used[0]))
        for c in used[1:]:
            out = out.when(F.col("p")[side] == c, F.col(c))
        return out

    return sets.withColumn("p", cell).select(
        F.col("p.a").alias("a"), F.col("p.b").alias("b"), pick("a").alias("x"), pick("b").alias("y"), "n"
    )


def dense_counts(codes: DataFrame, sizes: dict[str, int], pairs: list[tuple[str, str]]) -> DataFrame:
    """(a, b, x, y, n) without Expand: each task adds dense count arrays of known size, then slots are summed.

    A pair (a, a) stands for the values of a alone. A task's arrays hold sum of N_a * N_b counts, whatever it reads.
    """
    names = [c for c in codes.columns if c != "n"]

    def count(batches):
        total = {p: np.zeros(sizes[p[0]] * (sizes[p[1]] if p[0] != p[1] else 1), np.int64) for p in pairs}
        for pdf in batches:
            w = pdf["n"].to_numpy() if "n" in pdf else None
            for a, b in pairs:
                key = pdf[a].to_numpy() if a == b else pdf[a].to_numpy() * sizes[b] + pdf[b].to_numpy()
                got = np.bincount(key, weights=w, minlength=len(total[a, b]))
                total[a, b] += got.astype(np.int64)
        for i, p in enumerate(pairs):
            at = np.flatnonzero(total[p])
            if len(at):
                yield pd.DataFrame({"p": np.int32(i), "slot": at, "n": total[p][at]})

    merged = codes.select(*names, *(["n"] if "n" in codes.columns else [])).mapInPandas(
        count, "p int, slot long, n long"
    ).groupBy("p", "slot").agg(F.sum("n").alias("n"))
    label = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.lit(sizes[b] if a != b else 1).alias("w")) for a, b in pairs])
    return merged.withColumn("l", F.get(label, "p")).select(
        F.col("l.a").alias("a"), F.col("l.b").alias("b"),
        F.floor(F.col("slot") / F.col("l.w")).cast("int").alias("x"), (F.col("slot") % F.col("l.w")).cast("int").alias("y"), "n",
    )


#: Count slots that a task of `pair_counts` may hold: 64 MB.
MOST_SLOTS = 8_000_000

#: Count slots of a piece that `dense_groups` adds up in one task: half a megabyte.
CHUNK = 65_536


def pair_counts(codes: DataFrame, sizes: dict[str, int], pairs: list[tuple[str, str]]) -> DataFrame:
    """(a, b, x, y, n) of the attributes alone (as pairs (a, a)) and of `pairs`, without shuffling rows.

    Tasks add dense arrays while all of them together stay within MOST_SLOTS; pairs beyond that, largest first,
    are counted by grouping sets, whose partial sums shrink rows to cells before the shuffle.
    """
    room = MOST_SLOTS - sum(sizes.values())
    dense = [(a, a) for a in codes.columns if a != "n"]
    sparse = []
    for a, b in sorted(pairs, key=lambda p: sizes[p[0]] * sizes[p[1]]):
        room -= sizes[a] * sizes[b]
        (dense if room >= 0 else sparse).append((a, b))
    out = dense_counts(codes, sizes, dense)
    return out.unionByName(contingencies(codes, sparse)) if sparse else out


def dense_groups(codes: DataFrame, sizes: dict[str, int], sets: list[tuple[str, ...]], weight: str | None = None) -> dict[tuple[str, ...], np.ndarray]:
    """{attributes: counts of their groups, one axis per attribute}, or sums of the column `weight`, as arrays on the driver.

    All sets are counted in one pass while their arrays stay within MOST_SLOTS, and in as few passes as that takes beyond; one of over
    25 million groups is refused. Tasks hand on their arrays in pieces of CHUNK slots, one task adds the pieces of one place, and the
    driver receives the sums as bytes, not as rows.
    """
    shape = {s: tuple(sizes[a] for a in s) for s in sets}
    room, out, passes = 0, {}, []
    for s in shape:
        slots = int(np.prod(shape[s]))
        if slots > 25_000_000:
            raise ValueError(f"{s}: {slots} groups are too many for the driver")
        if not passes or room + slots > MOST_SLOTS:
            passes.append([])
            room = 0
        passes[-1].append(s)
        room += slots
    kind = np.int64 if weight is None else np.float64
    for some in passes:

        def count(batches, some=some):
            total = [np.zeros(int(np.prod(shape[s])), kind) for s in some]
            for pdf in batches:
                w = None if weight is None else pdf[weight].to_numpy()
                codes_of = {a: pdf[a].to_numpy() for s in some for a in s}
                for s, t in zip(some, total, strict=True):
                    key = np.ravel_multi_index([codes_of[a] for a in s], shape[s])
                    if len(t) > 4 * len(key):
                        np.add.at(t, key, 1 if w is None else w)
                    else:
                        t += np.bincount(key, weights=w, minlength=len(t)).astype(kind)
            for i, t in enumerate(total):
                yield from pieces(i, t)

        def pieces(i, t):
            for at in range(0, len(t), CHUNK):
                piece = t[at : at + CHUNK]
                if piece.any():
                    yield pd.DataFrame({"p": np.int32(i), "slot": [at], "n": [zlib.compress(piece.tobytes(), 1)]})

        def added(batches):
            total = {}
            for pdf in batches:
                for place, blob in zip(zip(pdf["p"].tolist(), pdf["slot"].tolist(), strict=True), pdf["n"], strict=True):
                    piece = np.frombuffer(zlib.decompress(blob), kind)
                    total[place] = total[place] + piece if place in total else piece
            for (i, at), piece in total.items():
                yield pd.DataFrame({"p": np.int32(i), "slot": [at], "n": [zlib.compress(piece.tobytes(), 1)]})

        used = sorted({a for s in some for a in s})
        got = codes.select(*used, *([weight] if weight else [])).mapInPandas(count, "p int, slot long, n binary")
        sums = got.repartition("p", "slot").mapInPandas(added, "p int, slot long, n binary")
        flat = {s: np.zeros(int(np.prod(shape[s])), kind) for s in some}
        for p, at, blob in sums.toLocalIterator():
            piece = np.frombuffer(zlib.decompress(blob), kind)
            flat[some[p]][at : at + len(piece)] = piece
        out |= {s: flat[s].reshape(shape[s]) for s in some}
    return out


def predicate_stats(codes: DataFrame, predicates: dict[str, str]) -> DataFrame:
    """(stat, n): counts of arbitrary predicates over the codes, all in one scan."""
    rows = _counted(codes)
    counts = rows.agg(*[F.sum(F.when(F.expr(p), F.col("n")).otherwise(0)).alias(k) for k, p in predicates.items()])
    return counts.select(
        F.explode(F.array(*[F.struct(F.lit(k).alias("stat"), F.col(k).alias("n")) for k in predicates])).alias("s")
    ).select("s.stat", F.coalesce("s.n", F.lit(0)).cast("long").alias("n"))


def rect_targets(contingency: DataFrame, leaves: DataFrame) -> DataFrame:
    """(leaf_id, n): counts of leaves (leaf_id, x_codes, y_codes) from a contingency (x, y, n).

    Membership is joined by value, as ordering may make a leaf's codes any set.
    """
    xs = leaves.select("leaf_id", F.explode("x_codes").alias("x"))
    ys = leaves.select(F.col("leaf_id").alias("l2"), F.explode("y_codes").alias("y"))
    cells = contingency.join(xs, "x").join(ys, ["y"]).where("leaf_id = l2")
    found = cells.groupBy("leaf_id").agg(F.sum("n").alias("n"))
    return leaves.select("leaf_id").join(found, "leaf_id", "left").select(
        "leaf_id", F.coalesce("n", F.lit(0)).alias("n")
    )


def matrix_of(contingency: DataFrame, a: str, b: str, shape: tuple[int, int]) -> np.ndarray:
    """Dense count matrix of a pair on the driver; refuses more than 25 million cells."""
    if shape[0] * shape[1] > 25_000_000:
        raise ValueError(f"{a}, {b}: {shape} cells are too many for the driver")
    rows = contingency.where((F.col("a") == a) & (F.col("b") == b)).select("x", "y", "n").toPandas()
    out = np.zeros(shape, dtype=np.int64)
    out[rows["x"], rows["y"]] = rows["n"]
    return out
